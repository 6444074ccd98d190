from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from stepsql.config import RewardConfig
from stepsql.operators import advantage as adv
from stepsql.operators import reward as rw
from stepsql.operators import select as sel

SCHEMA = "qid int, traj_id int, step_no int, n_tokens int, score double, h_step double, outcome int"
ONE = [(1, 1, i + 1, 1, s, h, 1) for i, (s, h) in enumerate(zip((0.9, 0.6, 0.8), (0.3, 0.2, 0.1)))]
TWO = ONE + [(1, 2, 1, 1, 0.5, 0.4, 0), (1, 2, 2, 1, 0.4, 0.4, 0)]


def values(df, *cols):
    return [tuple(round(r[c], 6) for c in cols) for r in df.orderBy("qid", "traj_id", "step_no").collect()]


def frame(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


def test_literal_form(spark):
    got = rw.step_reward(frame(spark, ONE))
    assert values(got, "w", "prefix_score", "reward") == [(0.5, 0.9, 0.9), (0.166667, 0.825, 1.725), (0.0, 0.825, 2.55)]


def test_step_mode_guards_zero_weight(spark):
    got = rw.step_reward(frame(spark, ONE), RewardConfig(entropy_mode="step"))
    assert values(got, "prefix_score", "reward") == [(0.9, 0.9), (0.6, 1.5), (0.733333, 2.233333)]


def test_corpus_scope(spark):
    rows = ONE + [(9, 9, 1, 1, 0.5, 1.0, 0)]
    got = rw.step_reward(frame(spark, rows), RewardConfig(norm_scope="corpus")).where("qid = 1")
    assert values(got, "w", "prefix_score", "reward") == [(0.7, 0.9, 0.9), (0.5, 0.775, 1.675), (0.4, 0.78125, 2.45625)]


def test_advantages(spark):
    rows = TWO + [(9, 9, 1, 1, 0.5, 1.0, 0)]
    raw = adv.raw(rw.step_reward(frame(spark, rows), RewardConfig(norm_scope="corpus")))
    got = adv.standardise(raw).where("qid = 1")
    assert values(got, "adv_raw", "adv") == [(3.45625, 1.500333), (2.55625, 0.660333), (1.78125, -0.063), (0.975, -0.8155), (0.475, -1.282167)]
    assert values(adv.standardise(raw, "sample").where("qid = 1"), "adv")[0][0] == pytest.approx(1.6075 / 1.1978937, abs=1e-6)
    assert values(adv.standardise(raw).where("qid = 9"), "adv") == [(0.0,)]


def test_one_step_and_zero_entropy(spark):
    rows = [(1, 1, 1, 1, 0.7, 0.5, 1), (2, 1, 1, 1, 0.6, 0.0, 0), (2, 1, 2, 1, 0.2, 0.0, 0)]
    assert values(rw.step_reward(frame(spark, rows)), "w", "reward") == [(0.0, 0.7), (1.0, 0.6), (1.0, 1.0)]


def random_log(seed, chains=40):
    r = random.Random(seed)
    return [(q % 7, q, k, r.randint(1, 9), r.random(), r.random(), r.randint(0, 1)) for q in range(chains) for k in range(1, r.randint(1, 9) + 1)]


@pytest.mark.parametrize("mode", ["cumulative", "step", "mean_prefix"])
@pytest.mark.parametrize("scope", ["trajectory", "group", "corpus"])
def test_against_plain_python(spark, mode, scope):
    rows = random_log(5)
    got = {(r.traj_id, r.step_no): (r.prefix_score, r.reward) for r in rw.step_reward(frame(spark, rows), RewardConfig(mode, scope)).collect()}
    h = {}
    for q, t, k, _, _, e, _ in rows:
        before = [x[5] for x in rows if x[1] == t and x[2] <= k]
        h[t, k] = {"cumulative": sum(before), "step": e, "mean_prefix": sum(before) / len(before)}[mode]
    for q, t, k, *_ in rows:
        same = [h[x[1], x[2]] for x in rows if (x[1] == t if scope == "trajectory" else x[0] == q if scope == "group" else True)]
        top, total = max(same), 0.0
        for d in range(1, k + 1):
            w = [(1 - h[x[1], x[2]] / top, x[4]) for x in rows if x[1] == t and x[2] <= d]
            mass = sum(a for a, _ in w)
            low, high = min(s for _, s in w), max(s for _, s in w)
            p = sum(a * s for a, s in w) / mass if mass > 0 else sum(s for _, s in w) / len(w)
            assert low - 1e-9 <= p <= high + 1e-9
            total += p
        assert got[t, k] == pytest.approx((p, total), abs=1e-9)
        assert total <= k + 1e-9


def test_nested_equals_flat(spark):
    log = frame(spark, random_log(6))
    flat = {r.traj_id: r.reward for r in rw.trajectory_reward(rw.step_reward(log)).collect()}
    nested = {r.traj_id: r.r for r in rw.nest(log).select("traj_id", rw.nested_reward(F.col("steps")).alias("r")).collect()}
    assert flat == pytest.approx(nested, abs=1e-9)


def test_scaling_entropies_keeps_weights(spark):
    log = frame(spark, random_log(7))
    for scope in ("trajectory", "group", "corpus"):
        c = RewardConfig(norm_scope=scope)
        a, b = values(rw.step_reward(log, c), "w"), values(rw.step_reward(log.withColumn("h_step", 3 * F.col("h_step")), c), "w")
        assert a == b


def test_standardised_groups(spark):
    raw = adv.raw(rw.step_reward(frame(spark, random_log(8))))
    m = adv.standardise(raw).groupBy("qid").agg(F.avg("adv").alias("m"), F.stddev_pop("adv").alias("s")).collect()
    assert all(abs(r.m) < 1e-9 and abs(r.s - 1) < 1e-9 for r in m)
    moved = adv.standardise(raw.withColumn("adv_raw", F.col("adv_raw") + 5))
    assert values(moved, "adv") == values(adv.standardise(raw), "adv")


def test_loss_parts(spark):
    one = spark.range(1)
    s = lambda rho, a: one.select(adv.surrogate(F.lit(rho), F.lit(a)).alias("x")).first().x
    assert [s(1.0, 0.7), s(1.5, 1.0), s(0.5, 1.0), s(1.5, -1.0), s(0.5, -1.0)] == pytest.approx([0.7, 1.2, 0.5, -1.5, -0.8])
    k = lambda kind, a, b: one.select(adv.kl(kind, F.lit(a), F.lit(b)).alias("x")).first().x
    assert k("k3", -1.0, -1.0) == 0 and all(k("k3", -1.0, b) > 0 for b in (-3.0, -0.2))


CANDS = [(1, 0, 0.5, 0, "a"), (1, 1, 0.9, 1, "b"), (1, 2, 0.9, 0, "b"), (1, 3, 0.1, 1, None), (2, 0, 0.3, 1, "x"), (2, 1, 0.2, 0, "y"), (3, 0, 0.0, 0, None)]


def test_selection(spark):
    c = spark.createDataFrame(CANDS, "qid int, cand int, reward double, outcome int, result_key string")
    best = {r.qid: r.cand for r in sel.best_of_n(c.orderBy(F.desc("cand"))).collect()}
    assert best == {1: 1, 2: 0, 3: 0}
    assert {r.qid: r.cand for r in sel.best_of_n(c, 1).collect()} == {1: 0, 2: 0, 3: 0}
    assert {r.qid: (r.result_key, r.cand, r.votes) for r in sel.majority_vote(c).collect()} == {1: ("b", 1, 2), 2: ("x", 0, 1)}
    passed = {(r.qid, r.n): r.passed for r in sel.pass_at_n(c, (1, 2, 4)).collect()}
    chosen = {(r.qid, r.n): r.outcome for r in sel.best_curve(c, (1, 2, 4)).collect()}
    assert all(chosen[k] <= passed[k] for k in chosen) and passed[1, 1] <= passed[1, 2] <= passed[1, 4]
    assert {r.qid: r.wins for r in sel.pairwise_wins(c).where("cand = 1").collect()} == {1: 2, 2: 0}


def test_pareto(spark):
    p = spark.createDataFrame([("a", 1, 5.0), ("b", 2, 4.0), ("c", 2, 6.0), ("d", 3, 6.0), ("e", 4, 7.0)], "m string, n int, v double")
    assert sorted(r.m for r in sel.pareto(p, "n", "v").collect()) == ["a", "c", "e"]
