"""Accuracy, stability, error and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

# The error taxonomy, group and type.
TAXONOMY = (
    ("schema linking", "table selection"), ("schema linking", "column selection"), ("schema linking", "join keys"),
    ("schema linking", "hallucination"), ("schema linking", "condition"), ("schema linking", "null handling"),
    ("value retrieval", "format"), ("value retrieval", "manipulation"),
    ("operation", "math formula"), ("operation", "aggregation"), ("operation", "complex operation"),
    ("information", "filter condition"), ("information", "order/limit"), ("information", "return format"),
    ("other", "domain knowledge"), ("other", "invalid query"),
)


def accuracy(outcomes: DataFrame, *by: str) -> DataFrame:
    """by..., questions, accuracy in percent."""
    return outcomes.groupBy(*by).agg(F.count("*").alias("questions"), (100 * F.avg("outcome")).alias("accuracy"))


def ood_rollup(outcomes: DataFrame) -> DataFrame:
    """family, set_name, accuracy: every set, the unweighted mean of each family's sets, and of all sets."""
    sets = accuracy(outcomes, "family", "set_name")
    return sets.select("family", "set_name", "accuracy").unionByName(
        sets.groupBy("family").agg(F.avg("accuracy").alias("accuracy")).select("family", F.lit("(mean)").alias("set_name"), "accuracy")
    ).unionByName(sets.agg(F.avg("accuracy").alias("accuracy")).select(F.lit("(all)").alias("family"), F.lit("(mean)").alias("set_name"), "accuracy"))


def stability(curve: DataFrame, warm_up: int, tolerance: float) -> DataFrame:
    """method, last, mean, std, peak, converged: of the rounds after warm_up; converged is the first round from which the
    value stays within the tolerance of the last."""
    ends = curve.groupBy("method").agg(F.max_by("value", "round").alias("last"), F.max("value").alias("peak"))
    far = curve.join(ends, "method").where(F.abs(F.col("value") - F.col("last")) > tolerance).groupBy("method").agg(F.max("round").alias("off"))
    late = curve.where(F.col("round") > warm_up).groupBy("method").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("std"))
    return ends.join(late, "method").join(far, "method", "left").select("method", "last", "mean", "std", "peak", (F.coalesce("off", F.lit(0)) + 1).alias("converged"))


def taxonomy_table(errors: DataFrame, questions: DataFrame) -> DataFrame:
    """grp, error_type, errors, share in percent of the rows of questions; subtotals a group and the total are rows with '(all)'."""
    rolled = errors.rollup("grp", "error_type").agg(F.count("*").alias("errors")).crossJoin(F.broadcast(questions.agg(F.count("*").alias("asked"))))  # one row
    return rolled.select(F.coalesce("grp", F.lit("(all)")).alias("grp"), F.coalesce("error_type", F.lit("(all)")).alias("error_type"), "errors", (100 * F.col("errors") / F.col("asked")).alias("share"))


def error_delta(errors: DataFrame, before: str, after: str) -> DataFrame:
    """error_type, before, after, delta, reduction in percent between two methods."""
    t = errors.groupBy("error_type").agg(F.count_if(F.col("method") == before).alias("before"), F.count_if(F.col("method") == after).alias("after"))
    return t.select("error_type", "before", "after", (F.col("after") - F.col("before")).alias("delta"), F.try_divide(100 * (F.col("before") - F.col("after")), F.col("before")).alias("reduction"))


def scaling_fit(points: DataFrame) -> DataFrame:
    """One row: slope, intercept and r2 of accuracy on ln n."""
    x = F.ln("n")
    return points.agg(F.regr_slope("accuracy", x).alias("slope"), F.regr_intercept("accuracy", x).alias("intercept"), F.regr_r2("accuracy", x).alias("r2"))


def latency_breakdown(timings: DataFrame) -> DataFrame:
    """n, stage, seconds, share of all seconds at that n."""
    per = timings.groupBy("n", "stage").agg(F.percentile("seconds", 0.5).alias("seconds"))
    return per.withColumn("share", F.col("seconds") / F.sum("seconds").over(Window.partitionBy("n")))


def calibration(scored: DataFrame, bins: int = 10) -> DataFrame:
    """bin, rows, mean_score, mean_outcome over equal-width bins of score in [0, 1)."""
    b = F.least(F.floor(F.col("score") * bins), F.lit(bins - 1)).cast("int")
    return scored.groupBy(b.alias("bin")).agg(F.count("*").alias("rows"), F.avg("score").alias("mean_score"), F.avg("outcome").alias("mean_outcome"))


def bce(scored: DataFrame, label: str = "sigma", clamp: float = 1e-6) -> DataFrame:
    """One row: rows, loss (sum), mean_loss of the soft-label cross-entropy of column score against the label."""
    s = F.greatest(F.lit(clamp), F.least(F.lit(1 - clamp), F.col("score")))
    y = F.col(label)
    cost = -(y * F.ln(s) + (1 - y) * F.ln(1 - s))
    return scored.agg(F.count("*").alias("rows"), F.sum(cost).alias("loss"), F.avg(cost).alias("mean_loss"))
