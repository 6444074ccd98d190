"""Streams over events and step logs, with batch twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.operators.reward import TRAJECTORY, prefix_entropy
from stepsql.sources.carriers import trail_orders
from stepsql.sources.shared import written
from stepsql.sources.tables import table
from stepsql.streaming import rewards as st

from .carrier_sql import ORDERS, rewards
from .core import OFF, r8
from .registry import query

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = st.split_log(table(spark, sf_dir, "events").withColumn("s_", F.unix_seconds(F.col("ts").cast("timestamp"))), "s_")
    return st.stream_of(spark, path, EVENTS).withColumn("ts", F.col("ts").cast("timestamp"))


@query("SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by day, streamed; the complete table stands at the end."""
    s = events(spark, sf_dir).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return st.drain_table(s.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n"))


@query("SELECT (date_trunc('hour', ts) - INTERVAL 1 HOUR * k - INTERVAL 1 HOUR * (hour(ts) % 12))::TIMESTAMP AS start, count(*) AS n FROM events, (VALUES (0), (12)) AS x(k) GROUP BY ALL")
def op_stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in windows of a day that start every twelve hours."""
    s = events(spark, sf_dir).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n"))
    return st.drain_table(s.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n"))


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) SELECT user_id, sum(new)::BIGINT AS sessions, count(*) AS n FROM g GROUP BY user_id")
def op_stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions with pauses of up to six hours, streamed: how many and how many events a user; the complete table stands at the end."""
    pause = "21600 seconds 1 microsecond"  # a pause of just six hours is within
    s = events(spark, sf_dir).groupBy(F.session_window("ts", pause).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return st.drain_table(s.select("user_id", "n")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


@query("SELECT count(DISTINCT event_id) AS events FROM events")
def op_stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated events leave one row within the watermark."""
    e = events(spark, sf_dir)
    s = e.unionByName(events(spark, sf_dir)).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")
    return st.drain(s).agg(F.count("*").alias("events"))


@query("SELECT event_type, c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY ALL")
def op_stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    s = events(spark, sf_dir).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("event_type", "c_mktsegment").agg(F.count("*").alias("n"))
    return st.drain_table(s)


@query("SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def op_stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within an hour of a view, both sides streamed and bounded by watermarks."""
    e = events(spark, sf_dir)
    v = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"), F.col("ts").alias("seen")).withWatermark("seen", "1 hour")
    p = e.where("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("bought")).withWatermark("bought", "1 hour")
    j = v.join(p, F.expr("user_id = buyer and bought >= seen and bought <= seen + interval 1 hour"))
    return st.drain(j.select("view_id", "purchase_id"))


@query(f"WITH {rewards(ORDERS, scope='corpus')} SELECT qid, traj_id, step_no, round(prefix_score + {OFF}, 8) + 0.0 AS prefix_score, round(reward + {OFF}, 8) + 0.0 AS reward FROM rewarded")
def op_stream_reward(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running rewards of the order log as its steps arrive; tests hold them against the batch form."""
    log = written(trail_orders(spark, sf_dir))
    files = spark.sparkContext.defaultParallelism
    path = st.split_log(log, "step_no", key=TRAJECTORY, files=files)
    top = prefix_entropy(log).agg(F.max("h_prefix").alias("m")).first().m
    s = st.stream_of(spark, path, "qid bigint, traj_id bigint, step_no int, n_tokens int, score double, h_step double, outcome int", files)
    return r8(st.drain_rewards(s, top))


@query("""WITH c AS (SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) FILTER (event_id % 50 <> 0) AS n, count(*) FILTER (event_id % 50 = 0) AS late FROM events GROUP BY ALL),
seen AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events WHERE event_id % 50 <> 0)
SELECT start, CASE WHEN start + INTERVAL 1 DAY <= mark THEN n END AS n, CASE WHEN start + INTERVAL 1 DAY <= mark THEN late END AS late FROM c, seen""")
def op_stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts under a watermark of one hour when every fiftieth event arrives last: how many of a day counted, and how many came too late."""
    e = table(spark, sf_dir, "events").withColumn("s_", F.unix_seconds(F.col("ts").cast("timestamp")))
    path = st.split_log(e.withColumn("s_", F.when(F.col("event_id") % 50 == 0, F.lit(2_000_000_000)).otherwise(F.col("s_"))), "s_")
    s = st.stream_of(spark, path, EVENTS).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    kept = st.drain(s.select(F.col("window.start").alias("start"), "n"))
    every = e.groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w")).agg(F.count("*").alias("all")).select(F.col("w.start").alias("start"), "all")
    # days that no watermark has passed are still open
    return every.join(kept, "start", "left").select(F.col("start").cast("timestamp_ntz").alias("start"), "n", (F.col("all") - F.col("n")).alias("late"))
