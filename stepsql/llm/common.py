"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.sources.shared import written
from stepsql.sources.tables import spread


def pick(df: DataFrame, *names: str) -> DataFrame:
    """Just these columns, found by position: other columns, also ones whose names
    differ by case only or repeat, never clash. An exact name wins over one that
    differs by case; of repeated names the first counts."""
    have = df.columns
    lower = [c.lower() for c in have]
    at = [have.index(n) if n in have else lower.index(n.lower()) for n in names]
    if len(set(lower)) == len(lower):
        return df.select(*[F.col(f"`{have[i]}`").alias(n) for i, n in zip(at, names)])
    plain = df.toDF(*[f"c{i}" for i in range(len(have))])
    return plain.select(*[F.col(f"c{i}").alias(n) for i, n in zip(at, names)])


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table of the given folder; a small one is dealt out to all cores."""
    return spread(spark.read.parquet(f"{sf_dir}/{table}.parquet"))


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers, once a context, wherever they run."""
    sc = spark.sparkContext
    if getattr(sc, "_stepsql_sent", False):
        return
    top = Path(__file__).resolve().parents[1]
    folder = tempfile.mkdtemp(prefix="stepsql-zip-")  # on the driver alone: Spark copies the file to its workers
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    with zipfile.ZipFile(f"{folder}/{top.name}_package.zip", "w") as z:
        for f in sorted(top.rglob("*.py")):
            z.write(f, f"{top.name}/{f.relative_to(top)}")
    sc.addPyFile(f"{folder}/{top.name}_package.zip")
    sc._stepsql_sent = True


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], dict], schema: str, rows: int = 512) -> DataFrame:
    """mapInArrow over slices of at most `rows` rows, so that a worker's memory is bounded by
    that many texts. fn gets a slice and returns a dict of columns in schema order."""
    from pyspark.sql.types import StructType
    from pyspark.sql.pandas.types import to_arrow_schema

    ship(df.sparkSession)
    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, rows):
                out = fn(b.slice(at, rows))
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def filter_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], list], rows: int = 512) -> DataFrame:
    """The rows for which fn, given slices of at most `rows` rows, returns true; all columns, no shuffle."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, rows):
                part = b.slice(at, rows)
                yield part.filter(pa.array(fn(part), pa.bool_()))

    return df.mapInArrow(run, df.schema)


def crc_mod(column: str, k: int):
    """crc32 of a column as text, modulo k: the folds of the contracts."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % F.lit(k)


def tokenizer_file(name: str, folder: str | None = None) -> str:
    """The place of a public vocabulary file; folder replaces the installed one."""
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


__all__ = ["crc_mod", "filter_batches", "map_batches", "pick", "read", "ship", "tokenizer_file", "written"]
