"""The given tables as DataFrames and temporary views."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

from .shared import drop, written

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = NAMES) -> None:
    """One temporary view a table; views hold plans, not rows."""
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def spread(df: DataFrame) -> DataFrame:
    """A table of fewer files than there are cores, and of less than a split a core, dealt out to all cores: a small file often
    holds one row group, which one task would read and work on alone. Other tables stay as their files split."""
    spark = df.sparkSession
    cores = spark.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    split = int(spark._jsparkSession.sessionState().conf().filesMaxPartitionBytes())
    # files are only listed for tables that small
    return df.repartition(cores) if size <= cores * split and len(df.inputFiles()) < cores else df


@contextmanager
def dealt(spark: SparkSession, least: int = 1 << 17, most: int = 1 << 24) -> Iterator[None]:
    """Views of tables between these bytes, in fewer files than there are cores, read copies with a file a core meanwhile, written once: many queries over a
    file of one row group would each read it, and all that its rows are joined to, in one task."""
    cores, before, paths = spark.sparkContext.defaultParallelism, {}, []
    try:
        for name in NAMES:
            if not spark.catalog.tableExists(name):
                continue
            df = spark.table(name)
            size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
            if least <= size <= most and 0 < len(df.inputFiles()) < cores:
                copy = written(df.repartition(cores))
                before[name] = df
                paths += [f.rsplit("/", 1)[0] for f in copy.inputFiles()[:1]]
                copy.createOrReplaceTempView(name)
        yield
    finally:
        for name, df in before.items():
            df.createOrReplaceTempView(name)
        for path in paths:
            drop(spark, path)
