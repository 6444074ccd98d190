"""Choosing among candidates of a question: rows with qid, cand (0-based order of sampling), and what a rule needs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def best_of_n(cands: DataFrame, n: int | None = None, by: str = "reward") -> DataFrame:
    """The candidate with the highest `by` among the first n; ties go to the earlier one. One combined aggregate."""
    cands = cands if n is None else cands.where(F.col("cand") < n)
    others = [c for c in cands.columns if c != "qid"]
    top = cands.groupBy("qid").agg(F.max(F.struct(F.col(by).alias("b_"), (-F.col("cand")).alias("c_"), F.struct(*others).alias("row"))).alias("t"))
    return top.select("qid", "t.row.*")


def best_curve(cands: DataFrame, budgets: tuple[int, ...], by: str = "reward") -> DataFrame:
    """qid, n, cand, outcome: winners for every budget in one pass, a conditional aggregate each."""
    top = cands.groupBy("qid").agg(
        *[F.max(F.when(F.col("cand") < n, F.struct(F.col(by).alias("b"), (-F.col("cand")).alias("c"), F.col("outcome").alias("o")))).alias(f"n{n}") for n in budgets]
    )
    rows = F.array(*[F.struct(F.lit(n).alias("n"), (-F.col(f"n{n}.c")).alias("cand"), F.col(f"n{n}.o").alias("outcome")) for n in budgets])
    return top.select("qid", F.inline(rows))


def majority_vote(cands: DataFrame, n: int | None = None, weight: str | None = None) -> DataFrame:
    """qid, result_key, cand, votes: the result most candidates share (or with the largest weight sum), ties to the
    earliest; candidates without a result do not vote."""
    cands = (cands if n is None else cands.where(F.col("cand") < n)).where("result_key is not null")
    votes = cands.groupBy("qid", "result_key").agg((F.sum(weight) if weight else F.count("*")).alias("votes"), F.min("cand").alias("cand"))
    top = votes.groupBy("qid").agg(F.max(F.struct("votes", (-F.col("cand")).alias("c"), "result_key")).alias("t"))
    return top.select("qid", F.col("t.result_key").alias("result_key"), (-F.col("t.c")).alias("cand"), F.col("t.votes").alias("votes"))


def pass_at_n(cands: DataFrame, budgets: tuple[int, ...]) -> DataFrame:
    """qid, n, passed: whether any of the first n is right."""
    hit = cands.groupBy("qid").agg(*[F.max(F.when(F.col("cand") < n, F.col("outcome"))).alias(f"n{n}") for n in budgets])
    return hit.select("qid", F.inline(F.array(*[F.struct(F.lit(n).alias("n"), F.col(f"n{n}").alias("passed")) for n in budgets])))


def pass_at_n_estimate(cands: DataFrame, n: int) -> DataFrame:
    """qid, estimate: 1 - C(total - right, n) / C(total, n), as a product; 1 where fewer than n are wrong."""
    c = cands.groupBy("qid").agg(F.count("*").alias("total"), F.sum("outcome").alias("right"))
    miss = F.aggregate(F.sequence(F.lit(0), F.lit(n - 1)), F.lit(1.0), lambda a, i: a * (F.col("total") - F.col("right") - i) / (F.col("total") - i))
    return c.where(F.col("total") >= n).select("qid", F.when(F.col("total") - F.col("right") < n, F.lit(1.0)).otherwise(1 - miss).alias("estimate"))


def pairwise_wins(cands: DataFrame, by: str = "reward") -> DataFrame:
    """qid, cand, wins: how many others of its question each candidate beats, from its rank (no pairs are formed)."""
    order = Window.partitionBy("qid").orderBy(F.col(by))
    return cands.select("qid", "cand", (F.rank().over(order) - 1).alias("wins"))


def pareto(points: DataFrame, cost: str, value: str) -> DataFrame:
    """Points that no cheaper or equally cheap point matches in value. A reported curve has few points; they are ranked in one task."""
    rest = sorted(c for c in points.columns if c not in (cost, value))
    before = Window.orderBy(F.col(cost), F.desc(value), *rest).rowsBetween(Window.unboundedPreceding, -1)
    return points.withColumn("seen", F.max(value).over(before)).where(F.col("seen").isNull() | (F.col(value) > F.col("seen"))).drop("seen")
