"""Tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; where it is unset, a temporary folder, set as such, of a local session.
    A cluster without that setting is an error: its machines share no other folder."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            found = held.get()
        elif re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            found = tempfile.mkdtemp(prefix="stepsql-")
            atexit.register(shutil.rmtree, found, ignore_errors=True)
            spark.sparkContext.setCheckpointDir(found)
        else:
            raise RuntimeError("spark.checkpoint.dir has to name a folder that all executors share")
    return found.rstrip("/")


def _place(spark: SparkSession, path: str):
    """(file system, path) in the JVM."""
    sc = spark.sparkContext
    place = sc._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(sc._jsc.hadoopConfiguration()), place


def new_folder(spark: SparkSession) -> str:
    """A new folder for a table of this session. All of them go as the session's JVM ends, or by `clear`."""
    sc = spark.sparkContext
    top = getattr(sc, "_stepsql_folder", None)
    if top is None:
        top = f"{shared_folder(spark)}/steps/{sc.applicationId}-{uuid.uuid4().hex}"
        files, place = _place(spark, top)
        files.mkdirs(place)
        files.deleteOnExit(place)
        sc._stepsql_folder = top
    return f"{top}/{uuid.uuid4().hex}"


def clear(spark: SparkSession) -> None:
    """Remove the tables that this session has written; DataFrames over them can no longer be read."""
    sc = spark.sparkContext
    top = getattr(sc, "_stepsql_folder", None)
    if top:
        files, place = _place(spark, top)
        files.delete(place, True)
        sc._stepsql_folder = None


def drop(spark: SparkSession, path: str) -> None:
    """Remove one table that this session has written."""
    top = getattr(spark.sparkContext, "_stepsql_folder", None)
    files, place = _place(spark, path)
    if top and f"/{top.rsplit('/', 1)[-1]}/" in path:
        files.delete(place, True)


def written(df: DataFrame, options: dict[str, str] | None = None) -> DataFrame:
    """df as Parquet, written with these options, in the shared folder, read again: lineage ends there, and lost executors take nothing along."""
    path = new_folder(df.sparkSession)
    df.write.options(**(options or {})).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
