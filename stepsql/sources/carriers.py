"""Step and token logs derived from the given tables.

Each carrier has columns qid, traj_id, step_no, n_tokens, score, h_step, outcome. Orders are total, ties broken
by every column, so that other engines number steps alike.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tables import table

LINE_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_shipdate", "l_returnflag", "l_linestatus")


def trail_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers as questions, their orders as trajectories, line items as steps, however many."""
    order = Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER)
    lines = table(spark, sf_dir, "lineitem").withColumn("step_no", F.row_number().over(order))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(
        F.col("o_custkey").alias("qid"),
        F.col("o_orderkey").alias("traj_id"),
        "step_no",
        (1 + F.col("l_quantity").cast("int") % 5).alias("n_tokens"),
        F.greatest(F.lit(0.01), F.least(F.lit(0.99), 1 - 5 * F.col("l_discount"))).alias("score"),
        (0.05 + F.col("l_tax")).alias("h_step"),
        (F.col("o_orderstatus") == "F").cast("int").alias("outcome"),
    )


def trail_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users as questions, their weeks as trajectories, days as steps; entropies come from the bigram policy of event types."""
    tokens = event_tokens(spark, sf_dir)
    days = tokens.groupBy("qid", "traj_id", "day").agg(
        F.count("*").cast("int").alias("n_tokens"),
        F.avg("value").alias("v"),
        F.avg("entropy").alias("h_step"),
        F.max(F.struct("ts", "event_id", "token")).alias("last"),
    )
    week = Window.partitionBy("qid", "traj_id")
    return days.select(
        "qid",
        "traj_id",
        F.row_number().over(week.orderBy("day")).alias("step_no"),
        "n_tokens",
        (F.col("v") / (1 + F.col("v"))).alias("score"),
        "h_step",
        (F.max("last").over(week).getField("token") == "purchase").cast("int").alias("outcome"),
    )


def event_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as tokens: prev is the user's event before, logp that of the bigram policy, logp_ref that of the unigram
    policy, entropy that of the policy after prev ('^' at the start)."""
    own = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf_dir, "events").select(
        "event_id", "ts", "user_id", "value", F.col("event_type").alias("token"), F.coalesce(F.lag("event_type").over(own), F.lit("^")).alias("prev")
    )
    pairs = e.groupBy("prev", "token").agg(F.count("*").alias("n"))
    context = Window.partitionBy("prev")
    policy = pairs.withColumn("p", F.col("n") / F.sum("n").over(context)).withColumn("entropy", -F.sum(F.col("p") * F.ln("p")).over(context))
    single = e.groupBy("token").agg(F.count("*").alias("k"))
    total = single.agg(F.sum("k").alias("total"))
    reference = single.crossJoin(F.broadcast(total)).select("token", F.ln(F.col("k") / F.col("total")).alias("logp_ref"))  # one row
    # vocabularies of event types: as many rows as types and pairs of types
    return (
        e.join(policy.select("prev", "token", F.ln("p").alias("logp"), "entropy"), ["prev", "token"])
        .join(reference, "token")
        .select(
            F.col("user_id").alias("qid"),
            F.concat_ws("-", F.col("user_id").cast("string"), F.floor(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) / 7).cast("string")).alias("traj_id"),
            F.to_date("ts").alias("day"),
            "ts", "event_id", "token", "prev", "value", "logp", "logp_ref", "entropy",
        )
    )


def document_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled documents as completions: qid = source, steps = all lines, outcome = quality."""
    docs = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    return docs.select(F.col("source").alias("qid"), F.col("doc_id").alias("traj_id"), F.split("text", "\n").alias("steps"), F.col("quality").alias("outcome"))


def turn_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations as trajectories: a turn is a step, its words are tokens."""
    turns = table(spark, sf_dir, "conversations")
    last = Window.partitionBy("conv_id")
    return turns.select(
        (F.col("conv_id") % 10).alias("qid"),
        F.col("conv_id").alias("traj_id"),
        F.row_number().over(last.orderBy("turn", "role", "text")).alias("step_no"),
        F.size(F.split("text", " ")).alias("n_tokens"),
        "text",
        (F.max(F.struct("turn", "role")).over(last).getField("role") == "assistant").cast("int").alias("outcome"),
    )


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as trajectories of tags: qid = host, one row a tag in page order."""
    pages = table(spark, sf_dir, "pages")
    tags = F.regexp_extract_all("html", F.lit(r"<(/?[a-z][a-z0-9]*)"), F.lit(1))
    return pages.select(F.regexp_extract("url", r"://([^/]+)", 1).alias("qid"), F.col("page_id").alias("traj_id"), F.posexplode(tags).alias("pos", "token"))
