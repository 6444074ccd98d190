"""Joins that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, keys: list[str], at: str, take: list[str]) -> DataFrame:
    """left with the columns `take` of the latest row of right at or before left's `at`, by keys: a union and one window,
    so no pair of rows is formed. At equal times right rows count as earlier; of those the largest wins."""
    value = F.struct(*take)
    both = left.withColumn("side_", F.lit(1)).withColumn("row_", F.struct(*left.columns)).select(*keys, at, "side_", "row_", F.lit(None).cast(right.select(value.alias("v")).schema[0].dataType).alias("v_")).unionByName(
        right.select(*keys, at, F.lit(0).alias("side_"), F.lit(None).cast(left.select(F.struct(*left.columns).alias("v")).schema[0].dataType).alias("row_"), value.alias("v_"))
    )
    order = Window.partitionBy(*keys).orderBy(at, "side_", "v_").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last_", F.last("v_", ignorenulls=True).over(order)).where("side_ = 1").select("row_.*", *[F.col("last_").getField(c).alias(c) for c in take])
