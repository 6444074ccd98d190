"""Measures over derived logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.operators import measures as ms
from stepsql.sources.carriers import trail_orders
from stepsql.sources.tables import table

from .carrier_sql import LINES, ORDERS
from .core import r6
from .registry import query

_TYPES = ", ".join(f"({i}, '{g}', '{e}')" for i, (g, e) in enumerate(ms.TAXONOMY))
_ERRORS = f"k(i, grp, error_type) AS (VALUES {_TYPES}), errors AS (SELECT 'm' || (l_suppkey % 3) AS method, grp, error_type FROM lineitem JOIN k ON i = (l_partkey * l_linenumber) % 16 WHERE l_quantity > 25)"


def errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items read as annotated failures of three methods."""
    kinds = spark.createDataFrame([(i, g, e) for i, (g, e) in enumerate(ms.TAXONOMY)], "i bigint, grp string, error_type string")
    rows = table(spark, sf_dir, "lineitem").where("l_quantity > 25").select(F.concat(F.lit("m"), (F.col("l_suppkey") % 3).cast("string")).alias("method"), ((F.col("l_partkey") * F.col("l_linenumber")) % 16).alias("i"))
    return rows.join(F.broadcast(kinds), "i").select("method", "grp", "error_type")  # the taxonomy: 16 rows


@query(f"WITH {_ERRORS} SELECT coalesce(grp, '(all)') AS grp, coalesce(error_type, '(all)') AS error_type, count(*) AS errors, round(100 * count(*) / (SELECT count(*) FROM lineitem), 6) + 0.0 AS share FROM errors GROUP BY ROLLUP (grp, error_type)")
def error_taxonomy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(ms.taxonomy_table(errors(spark, sf_dir), table(spark, sf_dir, "lineitem")))


@query(f"WITH {_ERRORS}, t AS (SELECT error_type, count(*) FILTER (method = 'm0') AS before, count(*) FILTER (method = 'm2') AS after FROM errors GROUP BY error_type) SELECT *, after - before AS delta, round(100 * (before - after) / nullif(before, 0), 6) + 0.0 AS reduction FROM t")
def error_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(ms.error_delta(errors(spark, sf_dir), "m0", "m2"))


_CURVE = "c AS (SELECT event_type AS method, date_diff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS round, avg(value) AS value FROM events WHERE event_type IN ('view', 'click') GROUP BY ALL)"


@query(f"""WITH {_CURVE}, e AS (SELECT method, max_by(value, round) AS last, max(value) AS peak FROM c GROUP BY method),
f AS (SELECT method, max(round) AS off FROM c JOIN e USING (method) WHERE abs(value - last) > 5 GROUP BY method), l AS (SELECT method, avg(value) AS mean, stddev_samp(value) AS std FROM c WHERE round > 10 GROUP BY method)
SELECT method, round(last, 6) + 0.0 AS last, round(mean, 6) + 0.0 AS mean, round(std, 6) + 0.0 AS std, round(peak, 6) + 0.0 AS peak, (coalesce(off, 0) + 1)::INTEGER AS converged FROM e JOIN l USING (method) LEFT JOIN f USING (method)""")
def training_stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stability of daily means, read as dev accuracy by round."""
    e = table(spark, sf_dir, "events").where(F.col("event_type").isin("view", "click"))
    curve = e.groupBy(F.col("event_type").alias("method"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("round")).agg(F.avg("value").alias("value"))
    return r6(ms.stability(curve, 10, 5.0))


_SETS = "o AS (SELECT CASE WHEN o_custkey % 5 < 3 THEN 'robust' ELSE 'cross' END AS family, 'set' || (o_custkey % 5) AS set_name, (o_orderstatus = 'F')::INTEGER AS outcome FROM orders)"


@query(f"WITH {_SETS}, s AS (SELECT family, set_name, 100 * avg(outcome) AS a FROM o GROUP BY ALL) SELECT family, set_name, round(a, 6) + 0.0 AS accuracy FROM s UNION ALL SELECT family, '(mean)', round(avg(a), 6) + 0.0 FROM s GROUP BY family UNION ALL SELECT '(all)', '(mean)', round(avg(a), 6) + 0.0 FROM s")
def ood_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").select(F.when(F.col("o_custkey") % 5 < 3, "robust").otherwise("cross").alias("family"), F.concat(F.lit("set"), (F.col("o_custkey") % 5).cast("string")).alias("set_name"), (F.col("o_orderstatus") == "F").cast("int").alias("outcome"))
    return r6(ms.ood_rollup(o))


@query("WITH g AS (SELECT CASE WHEN l_returnflag = 'A' THEN 'direct' ELSE 'chain' END AS format, CASE WHEN l_linestatus = 'F' THEN 'sft' ELSE 'rl' END AS training, (l_discount < 0.05)::INTEGER AS outcome FROM lineitem) SELECT format, training, count(*) AS n, round(100 * avg(outcome), 6) + 0.0 AS accuracy FROM g GROUP BY CUBE (format, training)")
def ablation_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = table(spark, sf_dir, "lineitem").select(F.when(F.col("l_returnflag") == "A", "direct").otherwise("chain").alias("format"), F.when(F.col("l_linestatus") == "F", "sft").otherwise("rl").alias("training"), (F.col("l_discount") < 0.05).cast("int").alias("outcome"))
    return r6(g.cube("format", "training").agg(F.count("*").alias("n"), (100 * F.avg("outcome")).alias("accuracy")))


@query()
def cost_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the jobs that run once before any question is answered: prefix labels and the fit of the score model."""
    import time

    from .registry import QUERIES

    rows = []
    for stage, name in (("label search", "mc_sigma"), ("score model", "scorer_fit")):
        began = time.perf_counter()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        rows.append((stage, name, time.perf_counter() - began))
    return spark.createDataFrame(rows, "stage string, job string, seconds double")


@query()
def schema_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links of question words to schema names for every wording of the bank: how many names each wording still reaches."""
    from stepsql.operators.schema import link_score
    from stepsql.sources import bank
    from stepsql.sources.tables import NAMES

    names = [(c,) for n in NAMES for c in [n, *table(spark, sf_dir, n).columns]]
    rows = [(q.qid, style, q.question if style == "plain" else bank.wording(q.question, style, q.qid)) for q in bank.QUESTIONS for style in ("plain", "synonym", "realistic", "knowledge")]
    asked = spark.createDataFrame(rows, "id bigint, style string, question string").withColumn("qid", F.concat_ws("-", "id", "style"))
    links = link_score(asked, spark.createDataFrame(names, "name string"))
    return links.join(asked.select("qid", "style"), "qid").groupBy("style").agg(F.count_if(F.col("shared") > 0).alias("exact_links"), F.count("*").alias("links"))


@query("""WITH s AS (SELECT round(score, 6) AS s, outcome FROM trail), r AS (SELECT outcome, avg(rk) OVER (PARTITION BY s) AS rk FROM (SELECT s, outcome, row_number() OVER (ORDER BY s) AS rk FROM s))
SELECT round((sum(rk) FILTER (outcome = 1) - count(*) FILTER (outcome = 1) * (count(*) FILTER (outcome = 1) + 1) / 2.0) / (count(*) FILTER (outcome = 1) * count(*) FILTER (outcome = 0)), 6) + 0.0 AS auc FROM r""".replace("WITH s AS", f"WITH {ORDERS}, s AS"))
def scorer_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Area under the curve of scores against outcomes, from counts by distinct score (as many as scores have digits)."""
    from pyspark.sql import Window

    by = trail_orders(spark, sf_dir).groupBy(F.round("score", 6).alias("s")).agg(F.count_if(F.col("outcome") == 1).alias("p"), F.count_if(F.col("outcome") == 0).alias("n"))
    below = F.coalesce(F.sum("n").over(Window.orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return r6(by.withColumn("below", below).agg((F.sum(F.col("p") * (F.col("below") + F.col("n") / 2)) / (F.sum("p") * F.sum("n"))).alias("auc")))


@query("""WITH bad AS (SELECT traj_id FROM completions WHERE len(list_filter(steps, lambda x: x = '')) > 0), good AS (SELECT c.* FROM completions c ANTI JOIN bad USING (traj_id)),
p AS (SELECT qid, outcome, steps, unnest(range(1, len(steps) + 1)) AS depth FROM good)
SELECT qid, depth::INTEGER AS depth, count(DISTINCT array_to_string(steps[1:depth], chr(31))) AS nodes, count(*) AS visits FROM p GROUP BY ALL""".replace("WITH bad AS", f"WITH {LINES}, bad AS"))
def clean_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prefix labels of the completions whose every step is well-formed (here: not empty)."""
    from stepsql.operators.labels import prefix_tree
    from stepsql.sources.carriers import document_lines

    good = document_lines(spark, sf_dir).where(~F.exists("steps", lambda s: s == ""))
    return prefix_tree(good).groupBy("qid", "depth").agg(F.count("*").alias("nodes"), F.sum("visits").alias("visits"))
