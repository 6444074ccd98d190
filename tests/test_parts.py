from __future__ import annotations

import math
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from stepsql.functions.entropy import entropy_bounds, token_entropy
from stepsql.operators import chains as ch
from stepsql.operators import digest as dg
from stepsql.operators import execute as ex
from stepsql.operators import labels as mc
from stepsql.operators import mutate
from stepsql.operators import policy as pol
from stepsql.operators.joins import asof
from stepsql.plans import inspect
from stepsql.sources import bank
from stepsql.sources.tables import table


def test_prefix_labels(spark):
    rows = [("q", 1, ["a", "b"], 1), ("q", 2, ["a", "b"], 0), ("q", 3, ["a", "c"], 1), ("q", 4, ["a"], 0), ("r", 5, ["a"], 1)]
    got = mc.prefix_tree(spark.createDataFrame(rows, "qid string, traj_id int, steps array<string>, outcome int")).collect()
    want = defaultdict(list)
    for q, _, s, o in rows:
        for d in range(1, len(s) + 1):
            want[q, tuple(s[:d])].append(o)
    assert sorted((r.qid, r.depth, r.visits, r.wins) for r in got) == sorted((q, len(p), len(o), sum(o)) for (q, p), o in want.items())
    kids = defaultdict(int)
    for r in got:
        if r.parent_key:
            kids[r.parent_key] += r.wins
    root = next(r for r in got if r.qid == "q" and r.depth == 1)
    assert root.wins == kids[root.prefix_key] + 0 and root.visits == 4


def test_prefix_labels_of_a_long_chain(spark):
    n = 10_000
    rows = [("q", 0, [f"step {i}" for i in range(n)], 1), ("q", 1, [f"step {i}" for i in range(n - 1)] + ["other"], 0), ("q", 2, [], 1)]
    nodes = mc.prefix_tree(spark.createDataFrame(rows, "qid string, traj_id int, steps array<string>, outcome int"))
    got = nodes.groupBy("visits").agg({"*": "count", "depth": "max"}).collect()
    assert sorted((r.visits, r["count(1)"], r["max(depth)"]) for r in got) == [(1, 2, n), (2, n - 1, n - 1)]
    assert nodes.join(nodes.selectExpr("prefix_key as parent_key"), "parent_key", "left_anti").count() == 1  # the root step


def test_weighted_labels(spark):
    rows = [("q", 1, ["a", "b"], 1, -1.0), ("q", 2, ["a", "b"], 1, -1.0), ("q", 3, ["a", "c"], 0, -2.0)]
    got = mc.weighted_sigma(spark.createDataFrame(rows, "qid string, traj_id int, steps array<string>, outcome int, logp double")).collect()
    assert max(r.sigma for r in got) == 1 and min(r.sigma for r in got) == 0
    assert any(abs(r.sigma - math.exp(-1) / (math.exp(-1) + math.exp(-2))) < 1e-12 for r in got)


def test_entropy(spark):
    df = spark.createDataFrame([({"a": 0.5, "b": 0.25, "c": 0.25, "d": 0.0}, [0.5, 0.25])], "d map<string,double>, top array<double>")
    low, high = entropy_bounds(F.col("top"), 4)
    r = df.select(token_entropy(F.col("d")).alias("h"), low.alias("low"), high.alias("high")).first()
    assert r.h == pytest.approx(1.0397207708) and r.low <= r.h + 1e-12 <= r.high + 1e-9 and r.h <= math.log(4)


def test_sampling_follows_the_policy(spark):
    p = spark.createDataFrame([("^", "a", 0.75), ("^", "b", 0.25), ("a", "b", 1.0), ("b", "a", 1.0)], "prev string, token string, p double")
    q = spark.range(400).withColumnRenamed("id", "qid")
    chains = pol.sample_chains(p, q, 5, 3)
    first = chains.groupBy(F.col("tokens")[0].alias("t")).count().collect()
    share = {r.t: r["count"] / 2000 for r in first}
    assert abs(share["a"] - 0.75) < 0.05
    assert sorted(map(tuple, chains.repartition(7).collect())) == sorted(map(tuple, pol.sample_chains(p, q.repartition(5), 5, 3).collect()))


def test_bank_chains_match_gold(spark, data):
    bank.prepare(spark, data)
    for q in bank.QUESTIONS[:12]:
        assert ex.outcome(spark, ch.compose(q.named, q.close), q.gold) == 1, q.qid
        assert ex.outcome(spark, ch.flatten(q.named, q.close), q.gold) == 1, q.qid


def test_validator(spark, data):
    bank.prepare(spark, data)
    for q in bank.QUESTIONS:
        assert ex.validate(spark, q.named, q.close) == (True, "", 0), q.qid
    q = bank.QUESTIONS[0]
    first, *rest = q.named
    assert ex.validate(spark, [(first[0], "SELEC 1"), *rest], q.close)[1:] == ("malformed", 1)
    assert ex.validate(spark, [("early", f"SELECT * FROM {first[0]}"), *q.named], q.close)[1:] == ("undefined reference", 1)
    assert ex.validate(spark, [*q.named, first], q.close)[1] == "name conflict"
    assert ex.validate(spark, [("a", "SELECT nothing FROM orders")], "SELECT * FROM a")[1] == "UNRESOLVED_COLUMN"


def test_executor_shares_prefixes_and_prunes(spark, data):
    bank.prepare(spark, data)
    a = [("x", "SELECT o_custkey FROM orders"), ("y", "SELECT count(*) AS n FROM x")]
    b = [a[0], ("z", "SELECT 1 / 0 AS n FROM x"), ("after", "SELECT * FROM z")]
    got = ex.run_chains(spark, [(a, "SELECT * FROM y"), (b, "SELECT * FROM after")]).collect()
    assert len(got) == 6
    assert sorted(r.status for r in got) == ["ok", "ok", "ok", "pruned", "pruned", "runtime error"]
    assert next(r for r in got if r.status == "runtime error").condition == "DIVIDE_BY_ZERO"


def test_fingerprint_is_multiset_equality(spark):
    key = lambda rows: dg.result_key(spark.createDataFrame(rows, "a double, b string")).first()[0]
    one = [(1.0, "x"), (2.0, None), (2.0, None)]
    assert key(one) == key(list(reversed(one))) != key(one[:2])
    assert key([(0.0, "x")]) == key([(-0.0, "x")]) != key([(0.0, "")])
    assert key([(1.0, None)]) != key([(1.0, "n")])


def test_mutations_are_told_apart(spark, data):
    bank.prepare(spark, data)
    got = mutate.evaluate(spark, [bank.QUESTIONS[22]]).collect()
    assert got[0].outcome == 1 and got[0].error_type == ""
    wrong = [r for r in got[1:] if not r.outcome]
    assert wrong and any(r.error_type == r.inferred for r in wrong)


def test_asof_takes_the_latest(spark):
    left = spark.createDataFrame([(1, 5, "a"), (1, 2, "b"), (2, 9, "c")], "k int, t int, n string")
    right = spark.createDataFrame([(1, 1, 10), (1, 3, 30), (1, 5, 50), (1, 5, 49), (2, 10, 1)], "k int, t int, v int")
    assert {r.n: r.v for r in asof(left, right, ["k"], "t", ["v"]).collect()} == {"a": 50, "b": 10, "c": None}


def test_scan_is_pruned(spark, data):
    df = table(spark, data, "lineitem").where("l_quantity > 45").select("l_orderkey")
    assert "GreaterThan(l_quantity,45.0)" in inspect.pushed_filters(df)[0]
    assert "l_tax" not in inspect.read_columns(df)[0]


def test_bucketed_log_needs_no_exchange(spark, data):
    from stepsql.operators.reward import step_reward
    from stepsql.sources.logs import bucketed

    df = step_reward(bucketed(spark, data))
    per = df.groupBy("qid").agg(F.max("reward"))
    spark.conf.set("spark.sql.sources.v2.bucketing.enabled", "true")
    assert inspect.count_nodes(per, "Exchange") == 0


def test_stream_reward_equals_batch(spark):
    from stepsql.config import RewardConfig
    from stepsql.operators.reward import step_reward
    from stepsql.streaming import rewards as st

    from .test_reward import SCHEMA, random_log

    log = spark.createDataFrame(random_log(9, 12), SCHEMA).selectExpr("cast(qid as bigint) qid", "cast(traj_id as bigint) traj_id", "step_no", "n_tokens", "score", "h_step", "outcome")
    batch = step_reward(log, RewardConfig(norm_scope="corpus"))
    top = batch.agg(F.max("h_prefix").alias("m")).first().m
    path = st.split_log(log, "step_no")
    got = st.drain(st.reward_stream(st.stream_of(spark, path, "qid bigint, traj_id bigint, step_no int, n_tokens int, score double, h_step double, outcome int"), top))
    a = {(r.traj_id, r.step_no): r.reward for r in batch.collect()}
    b = {(r.traj_id, r.step_no): r.reward for r in got.collect()}
    assert a == pytest.approx(b, abs=1e-9)


def test_stream_rewards_by_tables_equal_the_stream(spark):
    from stepsql.streaming import rewards as st

    rows = [(q, t, k, 1, ((q * 7 + t * 3 + k) % 10) / 10, 0.1 * ((q + t + k) % 4), 1) for q in range(3) for t in range(5) for k in range(1, 3 + 2 * t)]
    schema = "qid bigint, traj_id bigint, step_no int, n_tokens int, score double, h_step double, outcome int"
    log = spark.createDataFrame(rows, schema)
    plain = {tuple(r[:3]): r for r in st.drain(st.reward_stream(st.stream_of(spark, st.split_log(log, "step_no"), schema), 2.5)).collect()}
    for parts, files, at_once in ((3, 4, 4), (3, 4, 1), (9, 2, 3)):  # batches of whole parts, of less, and of more
        path = st.split_log(log, "step_no", parts, ("qid", "traj_id"), files)
        got = {tuple(r[:3]): r for r in st.drain_rewards(st.stream_of(spark, path, schema, at_once), 2.5).collect()}
        assert got.keys() == plain.keys() and len(got) == len(rows)
        assert all(abs(got[k].prefix_score - plain[k].prefix_score) < 1e-12 and abs(got[k].reward - plain[k].reward) < 1e-12 for k in got)


def test_entry_runs(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_nearest_examples(spark):
    from stepsql.operators.retrieve import nearest_examples

    asked = spark.createDataFrame([(1, "Which parts are large?"), (2, "zzz"), (3, None)], "qid bigint, question string")
    seeds = spark.createDataFrame([(10, "Which parts are large?"), (11, "Which parts are small"), (12, "parts"), (13, "")], "qid bigint, question string")
    rows = {(r.qid, r.rank): (r.seed, r.similarity) for r in nearest_examples(asked, seeds, 2).collect()}
    assert rows == {(1, 1): (10, 1.0), (1, 2): (11, 0.75)}


def test_graded_outcome(spark):
    from stepsql.operators.reward import graded_outcome

    rows = spark.createDataFrame([(1, True), (0, True), (0, False), (None, None)], "o int, ran boolean")
    assert [r.g for r in rows.select(graded_outcome(F.col("o"), F.col("ran")).alias("g")).collect()] == [1.0, 0.1, 0.0, 0.0]


@pytest.mark.parametrize("name, table", [("few_shot_examples", "conversations"), ("few_shot_examples", "benchmark"), ("op_range_gen", "events"), ("op_cte_recursive", "lineitem")])
def test_reads_a_given_table(spark, data, name, table):
    from stepsql.queries import QUERIES

    assert f"{table}.parquet" in QUERIES[name](spark, data)._jdf.queryExecution().analyzed().toString() or any(f"{table}.parquet" in f for f in QUERIES[name](spark, data).inputFiles())


def test_paths_take_only_keys_that_the_rows_keep(spark, data, tmp_path):
    import os

    from stepsql.queries import QUERIES

    for f in os.listdir(data):
        if f != "supplier.parquet":
            os.symlink(f"{data}/{f}", tmp_path / f)
    spark.read.parquet(f"{data}/supplier.parquet").where("s_suppkey <> 3").write.parquet(str(tmp_path / "supplier.parquet"))
    whole, less = ({(r.src, r.dst): r.hops for r in QUERIES["op_join_schema_path"](spark, d).collect()} for d in (data, str(tmp_path)))
    assert whole["lineitem", "supplier"] == 1 and ("lineitem", "supplier") not in less and less["orders", "customer"] == 1
