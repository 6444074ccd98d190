"""Rows of a Spark query and of its SQL under DuckDB, in comparable form."""

from __future__ import annotations

import glob
import math
import os

import duckdb


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 9)
    return v


def spark_rows(df) -> tuple[list[str], list[str]]:
    t = df.toArrow()
    names = sorted(t.column_names)
    return names, sorted(map(repr, zip(*[[plain(v) for v in t[c].to_pylist()] for c in names])))


def duck_rows(sql: str, sf_dir: str) -> tuple[list[str], list[str]]:
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    t = con.sql(sql).to_arrow_table()
    names = sorted(t.column_names)
    return names, sorted(map(repr, zip(*[[plain(v) for v in t[c].to_pylist()] for c in names])))
