"""Schema graphs: foreign keys as edges, and the shortest join paths between tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.sources.shared import written
from stepsql.sources.tables import table

EDGES = (
    ("lineitem", "l_orderkey", "orders", "o_orderkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("customer", "c_nationkey", "nation", "n_nationkey"),
    ("supplier", "s_nationkey", "nation", "n_nationkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("lineitem", "l_partkey", "part", "p_partkey"),
    ("lineitem", "l_suppkey", "supplier", "s_suppkey"),
)


def foreign_keys(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(EDGES, "src string, src_col string, dst string, dst_col string")


def kept_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst of the foreign keys that no row breaks: each finds its row in the other table."""
    checked = None
    for src, src_col, dst, dst_col in EDGES:
        rows, keys = table(spark, sf_dir, src).select(src_col), table(spark, sf_dir, dst).select(dst_col)
        lost = rows.join(keys, F.col(src_col) == F.col(dst_col), "left_anti").agg(F.count("*").alias("lost")).select(F.lit(src).alias("src"), F.lit(dst).alias("dst"), "lost")
        checked = lost if checked is None else checked.union(lost)
    return written(checked.where("lost = 0").select("src", "dst"))


def shortest_paths(edges: DataFrame, hops: int = 3) -> DataFrame:
    """src, dst, hops of the shortest undirected path of at most so many edges; grows with tables, not with rows."""
    u = edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    found = u.withColumn("hops", F.lit(1))
    step = found
    for k in range(2, hops + 1):
        step = step.select("src", F.col("dst").alias("mid")).join(u.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "dst").distinct().withColumn("hops", F.lit(k))
        found = found.union(step)
    return found.where("src <> dst").groupBy("src", "dst").agg(F.min("hops").alias("hops"))


def link_score(questions: DataFrame, names: DataFrame) -> DataFrame:
    """qid, name, shared, distance: overlap of question words with a schema name's words, and the least edit distance of any pair
    of them. names (column name) is the schema, small by nature."""
    words = questions.select("qid", F.explode(F.split(F.lower("question"), r"[^a-z0-9]+")).alias("word")).where("word <> ''")
    parts = names.select("name", F.explode(F.split(F.lower("name"), "_")).alias("part"))
    return words.join(F.broadcast(parts), F.levenshtein("word", "part", 2) >= 0).groupBy("qid", "name").agg(F.count_if(F.col("word") == F.col("part")).alias("shared"), F.min(F.levenshtein("word", "part")).alias("distance"))
