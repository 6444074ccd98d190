"""Rollout logs as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .carriers import trail_orders
from .shared import new_folder


def bucketed(spark: SparkSession, sf_dir: str, table: str = "step_log_bucketed", buckets: int = 16) -> DataFrame:
    """The order log as a table bucketed and sorted by question: rewards, group statistics and selection then need no exchange.
    Its files get a new folder each time, so what an earlier session left does not stand in the way."""
    spark.sql(f"DROP TABLE IF EXISTS {table}")
    trail_orders(spark, sf_dir).write.bucketBy(buckets, "qid").sortBy("qid", "traj_id", "step_no").option("path", new_folder(spark)).saveAsTable(table)
    return spark.table(table)


def read_log(spark: SparkSession, path: str) -> DataFrame:
    """A step log of a real model: Parquet with qid, traj_id, step_no, n_tokens, score, h_step, outcome."""
    log = spark.read.parquet(path)
    missing = {"qid", "traj_id", "step_no", "n_tokens", "score", "h_step", "outcome"} - set(log.columns)
    if missing:
        raise ValueError(f"the log lacks {sorted(missing)}")
    return log
