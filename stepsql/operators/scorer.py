"""Step score models: soft-label cross-entropy by weighted rows, through pyspark.ml."""

from __future__ import annotations

from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import GBTClassifier, LogisticRegression
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fit_scorer(rows: DataFrame, features: list[str], label: str = "sigma", kind: str = "logreg", penalty: float = 0.01) -> PipelineModel:
    """A label of sigma is two rows, 1 with weight sigma and 0 with weight 1 - sigma: the same objective."""
    two = rows.select(*features, F.inline(F.array(F.struct(F.lit(1.0).alias("y"), F.col(label).cast("double").alias("weight")), F.struct(F.lit(0.0).alias("y"), (1 - F.col(label)).cast("double").alias("weight"))))).where("weight > 0")
    model = LogisticRegression(labelCol="y", weightCol="weight", featuresCol="features", maxIter=50, regParam=penalty) if kind == "logreg" else GBTClassifier(labelCol="y", weightCol="weight", featuresCol="features", maxIter=10, seed=7)
    return Pipeline(stages=[VectorAssembler(inputCols=features, outputCol="features"), model]).fit(two)


def score(model: PipelineModel, rows: DataFrame) -> DataFrame:
    """rows with score, the probability of success; the model stays as it is."""
    return model.transform(rows).withColumn("score", vector_to_array("probability")[1]).drop("features", "rawPrediction", "probability", "prediction")
