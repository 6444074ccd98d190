"""Operators, sources, sinks and functions that step chains use: one query each."""

from __future__ import annotations

import pandas as pd

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stepsql.operators.schema import EDGES, foreign_keys, kept_keys, shortest_paths
from stepsql.sources.shared import new_folder
from stepsql.sources.tables import register, table

from .carrier_sql import EVENTS, ORDERS, rewards
from .core import OFF, r6, r8
from .registry import query

W = Window


def t(spark: SparkSession, d: str, name: str, *cols: str) -> DataFrame:
    df = table(spark, d, name)
    return df.select(*cols) if cols else df


def same(name: str, sql: str, *views: str) -> None:
    """A query whose text both engines run alike."""

    @query(sql, name)
    def run(spark: SparkSession, d: str) -> DataFrame:
        register(spark, d, views)
        return spark.sql(sql)


# --- scans, sources, sinks ------------------------------------------------------------------------


@query("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '2000-01-01'")
def op_scan_pruned(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").where(F.col("l_shipdate") >= F.lit("2000-01-01").cast("timestamp")).select("l_orderkey", "l_partkey", "l_quantity")


def _roundtrip(kind: str) -> None:
    @query("SELECT n_nationkey, n_name, n_regionkey FROM nation", f"op_{kind}_roundtrip")
    def run(spark: SparkSession, d: str) -> DataFrame:
        df = t(spark, d, "nation", "n_nationkey", "n_name", "n_regionkey")
        path = f"{new_folder(spark)}/nation.{kind}"
        df.write.mode("overwrite").format(kind).save(path)
        return spark.read.schema(df.schema).format(kind).load(path)


for _kind in ("csv", "json", "orc", "parquet"):
    _roundtrip(_kind)


@query("SELECT o_orderkey, o_custkey, o_totalprice FROM orders WHERE o_orderstatus = 'F'")
def op_partitioned_write(spark: SparkSession, d: str) -> DataFrame:
    """Orders written by status; one partition is read again."""
    path = f"{new_folder(spark)}/orders"
    t(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey", "o_totalprice")


@query(f"WITH {ORDERS} SELECT qid, count(*) AS steps, round(avg(score) + {OFF}, 8) + 0.0 AS mean_score FROM trail GROUP BY qid")
def op_bucketed_log(spark: SparkSession, d: str) -> DataFrame:
    """The step log as a table bucketed by question, whose group statistics need no exchange."""
    from stepsql.sources.logs import bucketed

    log = bucketed(spark, d)
    return r8(log.groupBy("qid").agg(F.count("*").alias("steps"), F.avg("score").alias("mean_score")))


same("op_temp_view", "SELECT n_regionkey, count(*) AS n FROM nation GROUP BY n_regionkey", "nation")
same("op_values", "SELECT k, v FROM (VALUES (1, 'a'), (2, 'b'), (3, NULL)) AS x(k, v)")


@query("SELECT unnest(generate_series(first, last, INTERVAL 1 DAY))::DATE AS day FROM (SELECT min(ts)::DATE AS first, max(ts)::DATE AS last FROM events)")
def op_range_gen(spark: SparkSession, d: str) -> DataFrame:
    """Every day from the first event to the last, with or without events."""
    ends = t(spark, d, "events").agg(F.to_date(F.min("ts")).alias("first"), F.to_date(F.max("ts")).alias("last"))
    return ends.select(F.explode(F.sequence("first", "last")).alias("day"))


# --- projection, predicates -----------------------------------------------------------------------


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax) + 1e-7, 4) + 0.0 AS charge FROM lineitem")
def op_project_expr(spark: SparkSession, d: str) -> DataFrame:
    c = F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))
    return t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", (F.round(c + 1e-7, 4) + 0.0).alias("charge"))


@query("SELECT o_orderkey, CASE WHEN o_totalprice < 100000 THEN 'small' WHEN o_totalprice < 300000 THEN 'medium' ELSE 'large' END AS size FROM orders")
def op_case_when(spark: SparkSession, d: str) -> DataFrame:
    p = F.col("o_totalprice")
    return t(spark, d, "orders").select("o_orderkey", F.when(p < 100000, "small").when(p < 300000, "medium").otherwise("large").alias("size"))


@query("SELECT o_orderkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') AND o_orderdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1997-12-31' AND o_orderpriority LIKE '%URGENT%'")
def op_filter_in_between_like(spark: SparkSession, d: str) -> DataFrame:
    o = t(spark, d, "orders").where(F.col("o_orderdate").between(F.lit("1996-01-01").cast("timestamp"), F.lit("1997-12-31").cast("timestamp")) & F.col("o_orderpriority").like("%URGENT%"))
    c = t(spark, d, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY"))
    return o.join(c, o.o_custkey == c.c_custkey).select("o_orderkey")


@query("SELECT c_custkey, coalesce(o, -1) AS last_order, nullif(coalesce(o, -1), -1) AS again, o IS NOT DISTINCT FROM NULL AS none FROM customer LEFT JOIN (SELECT o_custkey, max(o_orderkey) AS o FROM orders WHERE o_totalprice > 400000 GROUP BY ALL) ON c_custkey = o_custkey")
def op_null_safe(spark: SparkSession, d: str) -> DataFrame:
    o = t(spark, d, "orders").where("o_totalprice > 400000").groupBy("o_custkey").agg(F.max("o_orderkey").alias("o"))
    j = t(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left")
    return j.select("c_custkey", F.coalesce("o", F.lit(-1)).cast("bigint").alias("last_order"), F.nullif(F.coalesce("o", F.lit(-1)).cast("bigint"), F.lit(-1).cast("bigint")).alias("again"), F.col("o").eqNullSafe(F.lit(None)).alias("none"))


@query("SELECT p_partkey, round(p_retailprice / nullif(p_size % 3, 0), 4) + 0.0 AS ratio, TRY_CAST(p_brand AS INTEGER) AS brand FROM part")
def op_try_arith(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "part").select("p_partkey", (F.round(F.try_divide("p_retailprice", F.col("p_size") % 3), 4) + 0.0).alias("ratio"), F.expr("try_cast(p_brand as int)").alias("brand"))


@query("SELECT DISTINCT p_brand, p_type FROM part")
def op_distinct(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "part", "p_brand", "p_type").distinct()


# --- joins ------------------------------------------------------------------------------------


def _join(how: str, sql: str) -> None:
    @query(f"SELECT o_orderkey, c_name FROM customer {sql} JOIN orders ON c_custkey = o_custkey", f"op_join_{how}")
    def run(spark: SparkSession, d: str) -> DataFrame:
        o = t(spark, d, "orders", "o_orderkey", "o_custkey")
        c = t(spark, d, "customer", "c_custkey", "c_name")
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), how).select("o_orderkey", "c_name")


for _how in ("inner", "left", "right", "full"):
    _join(_how, _how.upper())


@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def op_join_broadcast(spark: SparkSession, d: str) -> DataFrame:
    # nations: a fixed table of 25 rows
    return t(spark, d, "customer").join(F.broadcast(t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


def _hinted(name: str, hint: str) -> None:
    @query("SELECT o_custkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey", name)
    def run(spark: SparkSession, d: str) -> DataFrame:
        o, li = t(spark, d, "orders", "o_orderkey", "o_custkey"), t(spark, d, "lineitem", "l_orderkey")
        return o.hint(hint).join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n"))


_hinted("op_join_sortmerge", "merge")
_hinted("op_join_shufflehash", "shuffle_hash")


@query("SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def op_join_theta(spark: SparkSession, d: str) -> DataFrame:
    s = t(spark, d, "supplier")
    return s.alias("a").join(s.alias("b"), F.expr("a.s_nationkey = b.s_nationkey and a.s_acctbal < b.s_acctbal")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@query("SELECT r_name, c_mktsegment FROM region CROSS JOIN (SELECT DISTINCT c_mktsegment FROM customer)")
def op_join_cross(spark: SparkSession, d: str) -> DataFrame:
    # five regions by the few market segments
    return t(spark, d, "region", "r_name").crossJoin(t(spark, d, "customer", "c_mktsegment").distinct())


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def op_join_semi(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "customer", "c_custkey").join(t(spark, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def op_join_anti(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "customer", "c_custkey").join(t(spark, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


same("op_join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", "nation")


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAY")
def op_join_range(spark: SparkSession, d: str) -> DataFrame:
    li, o = t(spark, d, "lineitem"), t(spark, d, "orders")
    near = F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("interval 30 days"))
    return li.join(o, (F.col("l_orderkey") == F.col("o_orderkey")) & near).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


@query("SELECT p.event_id AS purchase, v.event_id AS view_ FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def op_join_asof(spark: SparkSession, d: str) -> DataFrame:
    from stepsql.operators.joins import asof

    e = t(spark, d, "events")
    p, v = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase")), e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_"))
    return asof(p, v, ["user_id"], "ts", ["view_"]).select("purchase", "view_")


_SESSIONS = """
g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
n AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM g),
s AS (SELECT user_id, session, min(ts) AS a, max(ts) AS b, count(*) AS n FROM n GROUP BY ALL)"""


def sessions(spark: SparkSession, d: str, hours: int = 6) -> DataFrame:
    """user_id, session, a, b, n: runs of a user's events with gaps of at most so many hours."""
    own = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.when(F.col("ts") - F.lag("ts").over(own) <= F.expr(f"interval {hours} hours"), 0).otherwise(1)
    n = t(spark, d, "events").withColumn("new", gap).withColumn("session", F.sum("new").over(own))
    return n.groupBy("user_id", "session").agg(F.min("ts").alias("a"), F.max("ts").alias("b"), F.count("*").alias("n"))


@query(f"WITH {_SESSIONS} SELECT x.user_id, count(*) AS overlaps FROM s x JOIN s y ON x.user_id = y.user_id + 1 AND x.a <= y.b AND y.a <= x.b GROUP BY ALL")
def op_join_interval(spark: SparkSession, d: str) -> DataFrame:
    """Overlapping sessions of neighbouring users."""
    s = sessions(spark, d)
    j = s.alias("x").join(s.alias("y"), F.expr("x.user_id = y.user_id + 1 and x.a <= y.b and y.a <= x.b"))
    return j.groupBy(F.col("x.user_id").alias("user_id")).agg(F.count("*").alias("overlaps"))


@query("SELECT r_name, round(sum(l_extendedprice * (1 - l_discount)) + 1e-5, 2) + 0.0 AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def op_join_multi(spark: SparkSession, d: str) -> DataFrame:
    j = t(spark, d, "lineitem").join(t(spark, d, "orders"), F.expr("l_orderkey = o_orderkey")).join(t(spark, d, "customer"), F.expr("o_custkey = c_custkey"))
    j = j.join(t(spark, d, "nation"), F.expr("c_nationkey = n_nationkey")).join(t(spark, d, "region"), F.expr("n_regionkey = r_regionkey"))
    return j.groupBy("r_name").agg((F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))) + 1e-5, 2) + 0.0).alias("revenue"))


_EDGES = "(VALUES ('lineitem', 'orders'), ('orders', 'customer'), ('customer', 'nation'), ('supplier', 'nation'), ('nation', 'region'), ('lineitem', 'part'), ('lineitem', 'supplier'))"


def _paths(edges: str) -> str:
    return f"""WITH RECURSIVE e AS ({edges}), u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
p AS (SELECT a AS src, b AS dst, 1 AS hops FROM u UNION ALL SELECT src, b, hops + 1 FROM p JOIN u ON dst = a WHERE hops < 3)
SELECT src, dst, min(hops)::INTEGER AS hops FROM p WHERE src <> dst GROUP BY src, dst"""


@query(_paths(f"SELECT * FROM {_EDGES} AS x(a, b)"))
def schema_paths(spark: SparkSession, d: str) -> DataFrame:
    return shortest_paths(foreign_keys(spark), 3)


@query(_paths(" UNION ALL ".join(f"SELECT '{src}' AS a, '{dst}' AS b WHERE NOT EXISTS (SELECT 1 FROM {src} WHERE NOT EXISTS (SELECT 1 FROM {dst} WHERE {key} = {col}))" for src, col, dst, key in EDGES)))
def op_join_schema_path(spark: SparkSession, d: str) -> DataFrame:
    """Join paths over the foreign keys that the tables' rows keep."""
    return shortest_paths(kept_keys(spark, d), 3)


# --- aggregations -------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(sum(l_extendedprice), 2) + 0.0 AS price, round(avg(l_discount), 6) + 0.0 AS discount, count(*) AS n FROM lineitem GROUP BY ALL")
def op_agg_basic(spark: SparkSession, d: str) -> DataFrame:
    g = t(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus")
    return g.agg(F.sum("l_quantity").alias("qty"), (F.round(F.sum("l_extendedprice"), 2) + 0.0).alias("price"), (F.round(F.avg("l_discount"), 6) + 0.0).alias("discount"), F.count("*").alias("n"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey")
def op_agg_distinct(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"))


@query("SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS finished, count(*) FILTER (o_totalprice > 200000) AS large FROM orders GROUP BY o_custkey")
def op_agg_filter(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("finished"), F.count_if(F.col("o_totalprice") > 200000).alias("large"))


@query("SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey HAVING count(*) > 600")
def op_agg_having(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600")


@query("SELECT l_returnflag, round(var_samp(l_quantity), 4) + 0.0 AS v, round(stddev_pop(l_quantity), 4) + 0.0 AS s, round(corr(l_quantity, l_extendedprice), 4) + 0.0 AS c, round(regr_slope(l_extendedprice, l_quantity), 4) + 0.0 AS slope FROM lineitem GROUP BY ALL")
def op_agg_stats(spark: SparkSession, d: str) -> DataFrame:
    g = t(spark, d, "lineitem").groupBy("l_returnflag")
    return r6(g.agg(F.var_samp("l_quantity").alias("v"), F.stddev_pop("l_quantity").alias("s"), F.corr("l_quantity", "l_extendedprice").alias("c"), F.regr_slope("l_extendedprice", "l_quantity").alias("slope")), 4)


@query("SELECT p_brand, arg_max(p_partkey, (p_retailprice, -p_partkey)) AS part FROM part GROUP BY p_brand")
def op_agg_maxby(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "part").groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", -F.col("p_partkey"))).alias("part"))


@query("SELECT p_type, round(quantile_cont(p_retailprice, 0.5), 4) + 0.0 AS median FROM part GROUP BY p_type")
def op_agg_percentile(spark: SparkSession, d: str) -> DataFrame:
    return r6(t(spark, d, "part").groupBy("p_type").agg(F.percentile("p_retailprice", 0.5).alias("median")), 4)


@query()
def op_agg_approx(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median"))


@query("SELECT user_id, array_to_string(list_sort(list_distinct(list(event_type))), ',') AS kinds FROM events GROUP BY user_id")
def op_agg_collect(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("kinds"))


_GEO = "SELECT r_name, n_name, c_mktsegment, c_acctbal FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
for _name, _by in (("op_grouping_sets", "GROUPING SETS ((r_name, n_name), (c_mktsegment), ())"), ("op_rollup", "ROLLUP (r_name, n_name, c_mktsegment)"), ("op_cube", "CUBE (r_name, n_name, c_mktsegment)")):
    same(_name, f"SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM ({_GEO}) GROUP BY {_by}", "customer", "nation", "region")


@query("SELECT year(o_orderdate)::INTEGER AS y, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY ALL")
def op_pivot(spark: SparkSession, d: str) -> DataFrame:
    p = t(spark, d, "orders").groupBy(F.year("o_orderdate").alias("y")).pivot("o_orderstatus", ["F", "O", "P"]).count()
    return p.select("y", *[F.coalesce(c, F.lit(0)).cast("bigint").alias(c.lower()) for c in ("F", "O", "P")])


@query("WITH p AS (SELECT s_suppkey, s_nationkey::DOUBLE AS nation, s_acctbal AS balance FROM supplier) SELECT s_suppkey, 'nation' AS field, nation AS value FROM p UNION ALL SELECT s_suppkey, 'balance', balance FROM p")
def op_unpivot(spark: SparkSession, d: str) -> DataFrame:
    p = t(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
    return p.unpivot("s_suppkey", ["nation", "balance"], "field", "value")


@query("SELECT o_custkey, array_to_string(list_sort(list(o_orderkey)), ',') AS orders_ FROM orders GROUP BY o_custkey")
def op_sort_agg(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "orders").groupBy("o_custkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list("o_orderkey")), lambda x: x.cast("string")), ",").alias("orders_"))


# --- windows ----------------------------------------------------------------------------------

_C = "PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey"
same("op_win_rank", f"SELECT c_custkey, row_number() OVER ({_C}) AS rn, CAST(rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS BIGINT) AS dr FROM customer".replace("row_number() OVER", "CAST(row_number() OVER").replace(" AS rn", " AS BIGINT) AS rn"), "customer")
same("op_win_ntile", f"SELECT c_custkey, CAST(ntile(4) OVER ({_C}) AS BIGINT) AS q, round(percent_rank() OVER ({_C}), 6) + 0e0 AS pr, round(cume_dist() OVER ({_C}), 6) + 0e0 AS cd FROM customer", "customer")
same("op_win_firstlast", f"SELECT c_custkey, first_value(c_custkey) OVER ({_C}) AS best, last_value(c_custkey) OVER ({_C} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS worst, nth_value(c_custkey, 2) OVER ({_C} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_ FROM customer", "customer")


@query("SELECT o_orderkey, date_diff('day', lag(o_orderdate) OVER w, o_orderdate)::INTEGER AS gap, lead(o_orderkey) OVER w AS next_ FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def op_win_laglead(spark: SparkSession, d: str) -> DataFrame:
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(spark, d, "orders").select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).alias("gap"), F.lead("o_orderkey").over(w).alias("next_"))


_DAYS = "days AS (SELECT o_orderdate::DATE AS day, sum(o_totalprice) AS s FROM orders GROUP BY ALL)"


def _days(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "orders").groupBy(F.to_date("o_orderdate").alias("day")).agg(F.sum("o_totalprice").alias("s"))


# windows by year: a calendar's days are bounded, and no window runs in one task over all rows
def _rolling(name: str, frame: str, build) -> None:
    @query(f"WITH {_DAYS} SELECT day, round({frame} + 1e-6, 2) + 0.0 AS v FROM days", name)
    def run(spark: SparkSession, d: str) -> DataFrame:
        return r6(_days(spark, d).select("day", (build(W.partitionBy(F.year("day")).orderBy("day")) + 1e-6).alias("v")), 2)


_Y = "PARTITION BY year(day) ORDER BY day"
_rolling("op_win_running", f"sum(s) OVER ({_Y} ROWS UNBOUNDED PRECEDING)", lambda w: F.sum("s").over(w.rowsBetween(W.unboundedPreceding, 0)))
_rolling("op_win_sliding", f"avg(s) OVER ({_Y} ROWS 6 PRECEDING)", lambda w: F.avg("s").over(w.rowsBetween(-6, 0)))
_rolling("op_win_reverse", f"sum(s) OVER ({_Y} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)", lambda w: F.sum("s").over(w.rowsBetween(0, W.unboundedFollowing)))


@query(f"WITH {_DAYS} SELECT day, round(sum(s) OVER (PARTITION BY year(day) ORDER BY date_diff('day', DATE '1990-01-01', day) RANGE BETWEEN 29 PRECEDING AND CURRENT ROW), 2) + 0.0 AS v FROM days")
def op_win_range(spark: SparkSession, d: str) -> DataFrame:
    w = W.partitionBy(F.year("day")).orderBy(F.datediff("day", F.lit("1990-01-01").cast("date"))).rangeBetween(-29, 0)
    return r6(_days(spark, d).select("day", F.sum("s").over(w).alias("v")), 2)


# --- sort, limit, top-k, sets ------------------------------------------------------------------------

same("op_sort_nulls", "SELECT c_custkey, nullif(c_mktsegment, 'BUILDING') AS seg FROM customer ORDER BY seg NULLS LAST, c_custkey DESC", "customer")
same("op_limit_offset", "SELECT s_suppkey, s_name FROM supplier ORDER BY s_suppkey LIMIT 10 OFFSET 10", "supplier")


@query("SELECT c_nationkey, c_custkey, total FROM (SELECT c_nationkey, c_custkey, round(sum(o_totalprice), 2) + 0.0 AS total FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY total DESC, c_custkey) <= 3")
def op_topk_group(spark: SparkSession, d: str) -> DataFrame:
    s = t(spark, d, "customer").join(t(spark, d, "orders"), F.expr("c_custkey = o_custkey")).groupBy("c_nationkey", "c_custkey").agg((F.round(F.sum("o_totalprice"), 2) + 0.0).alias("total"))
    return s.withColumn("r", F.row_number().over(W.partitionBy("c_nationkey").orderBy(F.desc("total"), "c_custkey"))).where("r <= 3").drop("r")


for _name, _op in (("op_union_all", "UNION ALL"), ("op_union", "UNION"), ("op_intersect", "INTERSECT"), ("op_intersect_all", "INTERSECT ALL"), ("op_except", "EXCEPT"), ("op_except_all", "EXCEPT ALL")):
    same(_name, f"SELECT c_nationkey AS k FROM customer {_op} SELECT s_nationkey AS k FROM supplier", "customer", "supplier")

# --- subqueries and named steps ----------------------------------------------------------------------

same("op_sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)", "orders")
same("op_sub_correlated", "SELECT o_orderkey FROM orders a WHERE o_totalprice >= (SELECT max(o_totalprice) FROM orders b WHERE b.o_custkey = a.o_custkey)", "orders")
same("op_sub_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA')", "customer", "nation", "region")
same("op_sub_exists", "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity > 49)", "supplier", "lineitem")
same("op_sub_not_exists", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')", "customer", "orders")
same("op_lateral", "SELECT c_custkey, x.o_orderkey FROM customer, LATERAL (SELECT max(o_orderkey) AS o_orderkey FROM orders WHERE o_custkey = c_custkey) AS x", "customer", "orders")
same("op_cte_chain", "WITH a AS (SELECT o_custkey, o_totalprice FROM orders WHERE o_orderstatus = 'F'), b AS (SELECT o_custkey, count(*) AS n FROM a GROUP BY o_custkey) SELECT n, count(*) AS customers FROM b GROUP BY n", "orders")
same("op_cte_multi_ref", "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT a.o_custkey, a.n FROM a JOIN (SELECT max(n) AS m FROM a) x ON a.n = x.m", "orders")
same("op_cte_shadow", "WITH nation AS (SELECT n_nationkey, n_name FROM nation WHERE n_regionkey = 2) SELECT n_name FROM nation", "nation")
same("op_cte_recursive", "WITH RECURSIVE k AS (SELECT l_linenumber AS n, count(*) AS c FROM lineitem GROUP BY l_linenumber), r(n, f) AS (SELECT n, c FROM k WHERE n = 1 UNION ALL SELECT k.n, r.f + k.c FROM r JOIN k ON k.n = r.n + 1) SELECT n, f FROM r", "lineitem")
same("op_derived_nested", "SELECT seg, n FROM (SELECT c_mktsegment AS seg, count(*) AS n FROM (SELECT c_custkey, c_mktsegment FROM customer WHERE c_acctbal > 0) AS x GROUP BY c_mktsegment) AS y WHERE n > 10", "customer")

# --- scalar functions ------------------------------------------------------------------------------

same("op_str_basic", "SELECT p_partkey, upper(p_name) AS u, substr(p_brand, 1, 4) AS s, concat(p_brand, '-', p_type) AS c, lpad(CAST(p_size AS STRING), 4, '0') AS l, trim(p_type) AS t, replace(p_name, ' ', '_') AS r FROM part".replace("STRING", "VARCHAR(9)"), "part")
same("op_hash", "SELECT doc_id, md5(text) AS m FROM documents", "documents")


@query("SELECT doc_id, regexp_extract(text, '[A-Za-z]+@[a-z.]+', 0) AS mail, regexp_replace(text, '[0-9]', '#', 'g') AS masked, len(regexp_extract_all(text, '[0-9]+')) AS numbers FROM documents")
def op_str_regex(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "documents").select("doc_id", F.regexp_extract("text", "[A-Za-z]+@[a-z.]+", 0).alias("mail"), F.regexp_replace("text", "[0-9]", "#").alias("masked"), F.size(F.regexp_extract_all("text", F.lit("[0-9]+"), F.lit(0))).cast("bigint").alias("numbers"))


same("op_str_distance", "SELECT p_partkey, CAST(levenshtein(p_name, 'blue steel') AS BIGINT) AS d FROM part", "part")


@query("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, date_trunc('month', o_orderdate)::DATE AS m, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS age, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE AS later, (dayofweek(o_orderdate) + 1)::INTEGER AS dow FROM orders")
def op_date(spark: SparkSession, d: str) -> DataFrame:
    o = F.col("o_orderdate")
    return t(spark, d, "orders").select("o_orderkey", F.year(o).alias("y"), F.quarter(o).alias("q"), F.trunc(o, "month").alias("m"), F.datediff(F.to_date(o), F.lit("1995-01-01").cast("date")).alias("age"), F.add_months(F.to_date(o), 1).alias("later"), F.dayofweek(o).alias("dow"))


@query("SELECT p_partkey, floor(p_retailprice)::BIGINT AS f, round(ln(p_retailprice), 6) + 0.0 AS l, round(sqrt(p_retailprice), 6) + 0.0 AS s, p_size % 7 AS m, round(pow(p_size, 1.5), 5) + 0.0 AS p, sign(p_size - 25)::DOUBLE AS g, least(greatest(floor((p_size - 0) / 10.0)::BIGINT + 1, 0), 6) AS b FROM part")
def op_math(spark: SparkSession, d: str) -> DataFrame:
    p = F.col("p_retailprice")
    return t(spark, d, "part").select("p_partkey", F.floor(p).alias("f"), (F.round(F.ln(p), 6) + 0.0).alias("l"), (F.round(F.sqrt(p), 6) + 0.0).alias("s"), (F.col("p_size") % 7).alias("m"), (F.round(F.pow("p_size", F.lit(1.5)), 5) + 0.0).alias("p"), F.signum(F.col("p_size") - 25.0).alias("g"), F.width_bucket(F.col("p_size").cast("double"), F.lit(0.0), F.lit(50.0), F.lit(5)).alias("b"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 5) + 0.0 AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_max(embedding) > 0.3 AS peak FROM embeddings")
def op_array_hof(spark: SparkSession, d: str) -> DataFrame:
    e = F.col("embedding")
    norm = F.sqrt(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    return t(spark, d, "embeddings").select("vec_id", (F.round(norm, 5) + 0.0).alias("norm"), F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("positive"), F.exists(e, lambda x: x > F.lit(0.3).cast("float")).alias("peak"))


@query("WITH w AS (SELECT conv_id, turn, list_distinct(string_split(text, ' ')) AS w FROM conversations), p AS (SELECT a.conv_id, a.turn, a.w AS x, b.w AS y FROM w a JOIN w b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1) SELECT conv_id, turn, round(len(list_intersect(x, y)) / len(list_distinct(list_concat(x, y))), 6) + 0.0 AS jaccard FROM p")
def op_array_set(spark: SparkSession, d: str) -> DataFrame:
    w = t(spark, d, "conversations").select("conv_id", "turn", F.array_distinct(F.split("text", " ")).alias("w"))
    p = w.alias("a").join(w.alias("b"), F.expr("a.conv_id = b.conv_id and b.turn = a.turn + 1"))
    return r6(p.select(F.col("a.conv_id").alias("conv_id"), F.col("a.turn").alias("turn"), (F.size(F.array_intersect("a.w", "b.w")) / F.size(F.array_union("a.w", "b.w"))).alias("jaccard")))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def op_map(spark: SparkSession, d: str) -> DataFrame:
    c = t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).cast("bigint").alias("clicks"), F.size(F.map_keys("m")).cast("bigint").alias("kinds"))


@query("SELECT s_suppkey, s_name, s_acctbal < 0 AS debt FROM supplier")
def op_struct(spark: SparkSession, d: str) -> DataFrame:
    s = t(spark, d, "supplier").select("s_suppkey", F.struct("s_name", (F.col("s_acctbal") < 0).alias("debt")).alias("x"))
    return s.select("s_suppkey", F.col("x").getField("s_name").alias("s_name"), "x.debt")


@query("SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events")
def op_json(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT conv_id, turn, unnest(string_split(text, ' ')) AS word FROM conversations")
def op_explode(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "conversations").select("conv_id", "turn", F.explode(F.split("text", " ")).alias("word"))


@query("SELECT conv_id, turn, unnest(range(len(w)))::INTEGER AS pos, unnest(w) AS word FROM (SELECT conv_id, turn, string_split(text, ' ') AS w FROM conversations)")
def op_posexplode(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "conversations").select("conv_id", "turn", F.posexplode(F.split("text", " ")).alias("pos", "word"))


@query("SELECT page_id, array_to_string(regexp_extract_all(html, '<(/?[a-z][a-z0-9]*)', 1), ' ') AS tags FROM pages")
def op_html_tags(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "pages").select("page_id", F.array_join(F.regexp_extract_all("html", F.lit("<(/?[a-z][a-z0-9]*)"), F.lit(1)), " ").alias("tags"))


@query("WITH s AS (SELECT vec_id AS seed, embedding AS a FROM embeddings WHERE vec_id < 5), p AS (SELECT seed, vec_id, round(list_dot_product(list_transform(a, lambda x: x::DOUBLE), list_transform(embedding, lambda x: x::DOUBLE)), 6) + 0.0 AS score FROM s JOIN embeddings ON vec_id <> seed) SELECT seed, vec_id, score FROM p QUALIFY row_number() OVER (PARTITION BY seed ORDER BY score DESC, vec_id) <= 5")
def op_knn_bruteforce(spark: SparkSession, d: str) -> DataFrame:
    """Five nearest examples of each of five seeds (few-shot retrieval): the seeds are a fixed handful, broadcast."""
    e = t(spark, d, "embeddings", "vec_id", "embedding")
    seeds = F.broadcast(e.where("vec_id < 5").select(F.col("vec_id").alias("seed"), F.col("embedding").alias("a")))
    dot = F.aggregate(F.zip_with("a", "embedding", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    p = e.join(seeds, F.col("vec_id") != F.col("seed")).select("seed", "vec_id", (F.round(dot, 6) + 0.0).alias("score"))
    return p.withColumn("r", F.row_number().over(W.partitionBy("seed").orderBy(F.desc("score"), "vec_id"))).where("r <= 5").drop("r")


# --- user-defined functions ---------------------------------------------------------------------------


@query("SELECT l_orderkey, l_linenumber, l_partkey, round(1 - (0.05 + l_tax) / 0.2, 6) + 0.0 AS w FROM lineitem")
def op_sql_udf(spark: SparkSession, d: str) -> DataFrame:
    """The certainty weight as a SQL function."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION certainty(h DOUBLE, top DOUBLE) RETURNS DOUBLE RETURN CASE WHEN top > 0 THEN 1 - h / top ELSE 1 END")
    return r6(t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.expr("certainty(0.05 + l_tax, 0.2)").alias("w")))


@query("SELECT user_id, round(-sum(p * ln(p)), 6) + 0.0 AS entropy FROM (SELECT user_id, count(*) / sum(count(*)) OVER (PARTITION BY user_id) AS p FROM events GROUP BY user_id, event_type) GROUP BY user_id")
def op_pandas_udf(spark: SparkSession, d: str) -> DataFrame:
    """Entropy by an Arrow-batched function, as a reference for the built-in form."""
    @F.pandas_udf("double")
    def entropy(p: pd.Series) -> pd.Series:
        import numpy as np

        return p.map(lambda x: float(-(np.array(x) * np.log(x)).sum()))

    c = t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    p = c.withColumn("p", F.col("n") / F.sum("n").over(W.partitionBy("user_id"))).groupBy("user_id").agg(F.collect_list("p").alias("p"))
    return r6(p.select("user_id", entropy("p").alias("entropy")))


@query(f"WITH {rewards(EVENTS)}, l AS (SELECT qid, traj_id, max_by(reward, step_no) AS reward FROM rewarded GROUP BY ALL) SELECT qid, traj_id, round(reward + {OFF}, 8) + 0.0 AS reward FROM l")
def op_udaf(spark: SparkSession, d: str) -> DataFrame:
    """Running reward as a grouped aggregate: a fold over the collected steps."""
    from stepsql.operators.reward import nest, nested_reward
    from stepsql.sources.carriers import trail_events

    return r8(nest(trail_events(spark, d)).select("qid", "traj_id", nested_reward(F.col("steps")).alias("reward")))


@query("SELECT doc_id, depth::INTEGER AS depth, list_reduce(list_prepend('', steps[1:depth]), lambda held, step: md5(held || chr(31) || step)) AS prefix_key FROM (SELECT doc_id, steps, unnest(range(1, len(steps) + 1)) AS depth FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS steps FROM documents))")
def op_udtf(spark: SparkSession, d: str) -> DataFrame:
    """A chain to the digests of its prefixes, by a table function."""

    @F.udtf(returnType="depth int, prefix_key string")
    class Prefixes:
        def eval(self, text: str):
            import hashlib

            held = ""
            for depth, step in enumerate((text or "").split("\n"), 1):
                held = hashlib.md5(f"{held}\x1f{step}".encode("utf-8", "surrogatepass")).hexdigest()
                yield depth, held

    spark.udtf.register("chain_prefixes", Prefixes)
    t(spark, d, "documents", "doc_id", "text").createOrReplaceTempView("chain_texts")
    return spark.sql("SELECT doc_id, depth, prefix_key FROM chain_texts, LATERAL chain_prefixes(text)")
