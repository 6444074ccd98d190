"""Reading plans: what tests and users ask of them, without touching Spark's internals beyond the explain text."""

from __future__ import annotations

import contextlib
import io
import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain(mode)
    return out.getvalue()


def count_nodes(df: DataFrame, name: str) -> int:
    """Nodes of that name in the plan's tree."""
    tree = plan_text(df, "simple")
    return len(re.findall(rf"(?m)^[\s:+\-*()0-9]*{name}\b", tree))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", plan_text(df))


def estimated_bytes(df: DataFrame) -> int:
    """The optimizer's size estimate of the result: the cost that a cost-aware reward may subtract, from no run."""
    found = re.search(r"sizeInBytes=([0-9.]+) ?([KMGTPE]?i?B)", plan_text(df, "cost"))
    if not found:
        return 0
    scale = {"B": 0, "KiB": 10, "MiB": 20, "GiB": 30, "TiB": 40, "PiB": 50, "EiB": 60}[found[2]]
    return int(float(found[1]) * 2**scale)
