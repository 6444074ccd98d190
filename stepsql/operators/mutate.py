"""Seeded mutations of gold chains, each of a known error type, and the inference of error types from failures."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from .chains import compose
from .execute import condition, run_text

# Error type, pattern, replacement. The first that changes the text applies; each yields one candidate.
MUTATIONS: tuple[tuple[str, str, str], ...] = (
    ("table selection", r"\bcustomer\b", "supplier"), ("table selection", r"\bFROM part\b", "FROM supplier"), ("table selection", r"\bFROM nation\b", "FROM region"),
    ("column selection", r"\bo_totalprice\b", "o_custkey"), ("column selection", r"\bp_retailprice\b", "p_size"), ("column selection", r"\bn_name\b", "n_nationkey"),
    ("join keys", r"\bo_custkey = c_custkey\b", "o_orderkey = c_custkey"), ("join keys", r"\bl_partkey = p_partkey\b", "l_suppkey = p_partkey"), ("join keys", r"\bn_regionkey = r_regionkey\b", "n_nationkey = r_regionkey"),
    ("hallucination", r"\b([a-z]_[a-z]+key)\b", r"\1_id"),
    ("condition", r" > ", " < "), ("condition", r" = 1996", " = 1997"), ("condition", r" <> ", " = "),
    ("null handling", r"\bLEFT JOIN\b", "JOIN"), ("null handling", r"\bFULL JOIN\b", "JOIN"),
    ("format", r"'ASIA'", "'Asia'"), ("format", r"'R'", "'r'"), ("format", r"'PROMO", "'Promo"),
    ("manipulation", r"round\(([a-z]+), [26]\)", r"round(\1, 0)"),
    ("math formula", r"\(1 - l_discount\)", "1"), ("math formula", r"avg\(", "sum("),
    ("aggregation", r"\bsum\(", "avg("), ("aggregation", r"count\(\*\)", "count(DISTINCT 1)"),
    ("complex operation", r"PARTITION BY [a-z_]+ ", ""), ("complex operation", r"GROUP BY ROLLUP \(([^)]*)\)", r"GROUP BY \1"),
    ("filter condition", r" WHERE [a-z_]+ = '[^']*'$", ""), ("filter condition", r" WHERE [a-z_]+ (>|<|<>) [a-z_]+( |$)", " "),
    ("order/limit", r" DESC", " ASC"), ("order/limit", r"LIMIT 1\b", "LIMIT 2"),
    ("return format", r"^SELECT ", "SELECT 1 AS extra, "),
    ("domain knowledge", r"o_orderstatus = 'P'", "o_orderstatus = 'O'"), ("domain knowledge", r"s_acctbal < 0", "s_acctbal < 100"),
    ("invalid query", r"\)([^)]*)$", r"\1"), ("invalid query", r"\bFROM\b", "FORM"),
)


def candidates(steps: list[tuple[str, str]], close: str) -> list[tuple[str, list[tuple[str, str]], str]]:
    """(error type, steps, close): gold first, under the type '', then a candidate for every type that can be injected."""
    out, seen = [("", steps, close)], {""}
    for kind, pattern, put in MUTATIONS:
        if kind in seen:
            continue
        for k in range(len(steps), -1, -1):  # the closing query first, then later steps before earlier ones
            text = close if k == len(steps) else steps[k][1]
            new = re.sub(pattern, put, text, count=1)
            if new != text:
                out.append((kind, steps, new) if k == len(steps) else (kind, [*steps[:k], (steps[k][0], new), *steps[k + 1 :]], close))
                seen.add(kind)
                break
    return out


def _parts(text: str) -> dict[str, list[str]]:
    t = text.lower()
    return {
        "tables": sorted(re.findall(r"\b(?:from|join)\s+([a-z_]\w*)", t)), "on": sorted(re.findall(r"\bon\s+([^()]*?)(?=\bjoin\b|\bleft\b|\bwhere\b|\bgroup\b|\border\b|\)|$)", t)),
        "joins": sorted(re.findall(r"\b(left|full|right|cross)\s+join\b", t)), "strings": sorted(re.findall(r"'[^']*'", text)), "aggs": sorted(re.findall(r"\b(sum|avg|count|min|max|median)\(", t)),
        "distinct": re.findall(r"count\(distinct", t), "over": sorted(re.findall(r"partition by [a-z_]+|rollup", t)), "order": re.findall(r"\bdesc\b|\basc\b|limit \d+", t),
        "where": sorted(re.findall(r"\bwhere\b", t)), "compare": re.findall(r"<>|<=|>=|<|>|=", t), "numbers": sorted(re.findall(r"\b\d+(?:\.\d+)?\b", t)), "columns": sorted(re.findall(r"\b[a-z]_[a-z]+\b", t)), "round": re.findall(r"round\([^,]*, \d", t),
    }


def infer(pred: str, gold: str, status: str, cond: str) -> str:
    """Error type of a failed prediction from its error condition, or else from the first clause that differs from gold's."""
    if status == "invalid":
        return {"PARSE_SYNTAX_ERROR": "invalid query", "UNRESOLVED_COLUMN": "hallucination", "TABLE_OR_VIEW_NOT_FOUND": "table selection"}.get(cond, "column selection")
    a, b = _parts(pred), _parts(gold)
    for kind, keys in (
        ("return format", ()), ("table selection", ("tables",)), ("null handling", ("joins",)), ("join keys", ("on",)), ("complex operation", ("over",)), ("aggregation", ("aggs", "distinct")),
        ("filter condition", ("where",)), ("order/limit", ("order",)), ("format", ("strings",)), ("condition", ("compare",)), ("manipulation", ("round",)), ("column selection", ("columns",)), ("math formula", ("numbers",)),
    ):
        if (kind == "return format" and "as extra" in pred.lower()) or any(a[k] != b[k] for k in keys):
            if kind == "format" and [s.lower() for s in re.findall(r"'[^']*'", pred)] != [s.lower() for s in re.findall(r"'[^']*'", gold)]:
                return "domain knowledge"
            return kind
    return "math formula"


def evaluate(spark: SparkSession, questions) -> DataFrame:
    """qid, cand, error_type, inferred, status, outcome, result_key, n_steps, seconds of every candidate; results are compared by fingerprint."""
    rows = []
    for q in questions:
        gold = run_text(spark, q.gold)
        for k, (kind, steps, close) in enumerate(candidates(q.named, q.close)):
            got = run_text(spark, compose(steps, close))
            right = int(got["status"] == "ok" and got["result_key"] == gold["result_key"])
            rows.append((q.qid, k, kind, "" if right else infer(compose(steps, close), compose(q.named, q.close), got["status"], got["condition"]), got["status"], right, got["result_key"], len(steps), got["seconds"]))
    return spark.createDataFrame(rows, "qid bigint, cand int, error_type string, inferred string, status string, outcome int, result_key string, n_steps int, seconds double")


__all__ = ["MUTATIONS", "candidates", "condition", "evaluate", "infer"]
