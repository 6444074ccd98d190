"""Examples for few-shot prompts: the seed questions most like a question, by the cosine of their word counts."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _weights(questions: DataFrame, key: str) -> DataFrame:
    """key, word, w: word counts of a question, divided by their length as a vector."""
    words = questions.select(key, F.explode(F.split(F.lower("question"), "[^a-z0-9]+")).alias("word")).where("word <> ''")
    counts = words.groupBy(key, "word").agg(F.count("*").alias("c"))
    norms = counts.groupBy(key).agg(F.sqrt(F.sum(F.col("c") * F.col("c"))).alias("norm"))
    return counts.join(norms, key).select(key, "word", (F.col("c") / F.col("norm")).alias("w"))


def nearest_examples(asked: DataFrame, seeds: DataFrame, k: int = 5) -> DataFrame:
    """qid, seed, similarity, rank (from 1) of the k seeds nearest to each asked question (rows with qid, question).

    Only pairs that share a word meet, through a join on words. Similarities are rounded to nine digits; ties go to
    the smaller seed. A question that shares no word with any seed has no rows."""
    own = _weights(asked, "qid")
    known = _weights(seeds.withColumnRenamed("qid", "seed"), "seed").withColumnRenamed("w", "v")
    pairs = own.join(known, "word").groupBy("qid", "seed").agg(F.round(F.sum(F.col("w") * F.col("v")), 9).alias("similarity"))
    place = Window.partitionBy("qid").orderBy(F.desc("similarity"), "seed")
    return pairs.withColumn("rank", F.row_number().over(place)).where(F.col("rank") <= k)


def copy_chain(steps: list[tuple[str, str]], close: str, linked: list[str], tables: tuple[str, ...]) -> tuple[list[tuple[str, str]], str]:
    """A seed's chain as a template: its tables, in the order of first use, are replaced by the tables that another question's words link to, best first."""
    used = list(dict.fromkeys(t for t in re.findall(r"(?i)\b(?:from|join)\s+([a-z_]\w*)", " ".join([q for _, q in steps] + [close])) if t in tables))
    swap = dict(zip(used, linked))
    put = lambda text: re.sub(r"(?i)(\b(?:from|join)\s+)([a-z_]\w*)", lambda m: m[1] + swap.get(m[2], m[2]), text)
    return [(n, put(q)) for n, q in steps], put(close)
