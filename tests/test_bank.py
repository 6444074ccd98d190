"""Experiments on the bank against plain forms, and the behaviour that they are to show."""

from __future__ import annotations

import math
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from stepsql.config import TrainConfig
from stepsql.operators import bankpolicy as bp
from stepsql.operators import bankrun
from stepsql.operators import chains as ch
from stepsql.operators import execute as ex
from stepsql.operators import digest as digest_module
from stepsql.operators.digest import digest
from stepsql.queries import QUERIES
from stepsql.queries import experiments as xp
from stepsql.sources import bank, tables

MENU = [(q, s, t, "" if t == 0 else f"kind{t}", f"text {q} {s} {t}") for q in (1, 2) for s in (1, 2) for t in range(3)]


@pytest.fixture(scope="module")
def policy(spark):
    rows = [("r", q, s, state, t, k, 0.3 * t - 0.5 * state * t + 0.1 * q * s) for q, s, t, k, _ in MENU for state in (0, 1)]
    return spark.createDataFrame(rows, "run string, qid bigint, slot int, state int, token int, error_type string, logit double")


def chance(policy) -> dict:
    held = defaultdict(dict)
    for r in policy.collect():
        held[r.run, r.qid, r.slot, r.state][r.token] = math.exp(r.logit)
    return {k: {t: e / sum(v.values()) for t, e in v.items()} for k, v in held.items()}


def test_samples_follow_the_policy(spark, policy):
    rows = bp.sample(policy, 3000, 1).where("qid = 1").collect()
    p = chance(policy)
    first = Counter(r.token for r in rows if r.step_no == 1)
    assert all(abs(first[t] / 3000 - p["r", 1, 1, 0][t]) < 0.03 for t in range(3))
    later = Counter((r.state, r.token) for r in rows if r.step_no == 2)
    slipped = sum(n for (s, _), n in later.items() if s)
    assert all(abs(later[1, t] / slipped - p["r", 1, 2, 1][t]) < 0.04 for t in range(3))
    assert all(r.chain.split("-")[-1] == str(r.token) and len(r.chain.split("-")) == r.step_no and r.state == int(r.step_no == 2 and not r.chain.startswith("0")) for r in rows)
    assert all(abs(r.p - p["r", 1, r.step_no, r.state][r.token]) < 1e-9 for r in rows)
    assert {r.chain for r in bp.sample(policy, 2, 1, greedy=True).where("step_no = 2").collect()} == {"2-0"}


def test_cold_start_counts(spark):
    menu = bp.menu_frame(spark, MENU)
    corpus = spark.createDataFrame([(1, 0, 1, 0, 0), (1, 0, 2, 0, 1), (1, 1, 1, 0, 0), (1, 1, 2, 0, 0)], "qid bigint, cand int, step_no int, state int, token int")
    got = {(r.qid, r.slot, r.state, r.token): math.exp(r.logit) for r in bp.cold_start(menu, corpus, "x", prior=2.0, alpha=1.0, spread=0.0).collect()}
    rate = {"": (3 + 1) / (4 + 4), "kind1": (1 + 1) / (4 + 4), "kind2": 1 / (4 + 4)}
    p0 = [v / sum(rate.values()) for v in rate.values()]
    for t, n in enumerate((1, 1, 0)):
        assert abs(got[1, 2, 0, t] - (n + 2 * p0[t]) / 4) < 1e-9
        assert abs(got[2, 1, 0, t] - p0[t]) < 1e-9  # no corpus: the prior
    assert abs(sum(got[2, 1, 1, t] for t in range(3)) - 1) < 1e-9


def table(spark, outcome) -> tuple:
    """Runs and scores of all chains of MENU."""
    runs, scores = [], []
    for q in (1, 2):
        for a in range(3):
            scores.append((q, f"{a}", 0.9 - 0.3 * a, 0.5))
            for b in range(3):
                scores.append((q, f"{a}-{b}", 0.8 - 0.2 * a - 0.1 * b, 0.1 * b))
                runs.append((q, f"{a}-{b}", 2, 2, outcome(a, b), "ok", f"k{a}{b}", "train", "T1", "d", "", ""))
    return (
        spark.createDataFrame(runs, "qid bigint, chain string, slot int, slots int, outcome int, status string, result_key string, split string, tier string, db string, first_error string, inferred string"),
        spark.createDataFrame(scores, "qid bigint, chain string, score double, orm double"),
    )


@pytest.mark.parametrize("run", ["step reward|1", "outcome only|1", "graded outcome|1"])
def test_update_equals_a_plain_gradient(spark, policy, run):
    config = TrainConfig(group=6, rate=0.7, clip=0.05, kl=0.1, inner=3, sharing=0.5, seed=2)
    runs, scores = table(spark, lambda a, b: int(a == 0))
    start = policy.withColumn("run", F.lit(run)).withColumn("ref", F.col("logit") * 0.9).select(*bp.CONTEXT, "token", "error_type", "ref", "logit")
    drawn = bp.sample(start, config.group, 1000 + config.seed).collect()
    got = {(r.qid, r.slot, r.state, r.token): r.logit for r in bp.update(start, scores, runs, config, 1).collect()}

    score = {(r.qid, r.chain): r.score for r in scores.collect()}
    chains = defaultdict(list)
    for r in drawn:
        chains[r.qid, r.cand].append(r)
    running = {k: np.cumsum([r.h_step for r in sorted(v, key=lambda r: r.step_no)]) for k, v in chains.items()}
    top = max(h.max() for h in running.values())
    steps = []
    for (q, c), v in chains.items():
        v.sort(key=lambda r: r.step_no)
        w = 1 - running[q, c] / top
        s = np.array([score[q, r.chain] for r in v])
        prefix = [np.sum(w[: k + 1] * s[: k + 1]) / w[: k + 1].sum() if w[: k + 1].sum() > 0 else s[: k + 1].mean() for k in range(len(v))]
        right = int(v[0].token == 0)
        for k, r in enumerate(v):
            raw = right + sum(prefix[k:]) if run.startswith("step") else float(right) if run.startswith("outcome") else (1.0 if right else 0.1)
            steps.append([q, r.step_no, r.state, r.token, raw, len(v)])
    for q in (1, 2):
        own = [s for s in steps if s[0] == q]
        x = np.array([s[4] for s in own])
        for s, a in zip(own, (x - x.mean()) / x.std() if x.std() > 0 else x * 0):
            s[4] = a
    kind = {(q, s, t): k for q, s, t, k, _ in MENU}
    logit = {(r.qid, r.slot, r.state, r.token): r.logit for r in start.collect()}
    ref = {(r.qid, r.slot, r.state, r.token): r.ref for r in start.collect()}

    def soft(z):
        e = {k: math.exp(v) for k, v in z.items()}
        total = defaultdict(float)
        for k, v in e.items():
            total[k[:3]] += v
        return {k: v / total[k[:3]] for k, v in e.items()}

    old, base = soft(logit), soft(ref)
    for _ in range(config.inner):
        p = soft(logit)
        gain, mass = defaultdict(float), defaultdict(float)
        for q, slot, state, token, a, n in steps:
            rho = p[q, slot, state, token] / old[q, slot, state, token]
            if (a >= 0 and rho < 1 + config.clip) or (a < 0 and rho > 1 - config.clip):
                gain[q, slot, state, token] += a * rho / n / config.group
                mass[q, slot, state] += a * rho / n / config.group
        kl = defaultdict(float)
        for k in p:
            kl[k[:3]] += p[k] * math.log(p[k] / base[k])
        g = {k: gain[k] - p[k] * mass[k[:3]] - config.kl * p[k] * (math.log(p[k] / base[k]) - kl[k[:3]]) for k in p}
        shared = defaultdict(list)
        for k, v in g.items():
            shared[kind[k[0], k[1], k[3]], k[2]].append(v)
        logit = {k: logit[k] + config.rate * (g[k] + config.sharing * np.mean(shared[kind[k[0], k[1], k[3]], k[2]])) for k in logit}
    assert got.keys() == logit.keys() and all(abs(got[k] - logit[k]) < 1e-9 for k in got)


def test_search_counts_every_walk(spark, policy):
    runs, _ = table(spark, lambda a, b: int(a == 0 and b == 0))
    nodes = bp.search_tree(policy, runs, 12).collect()
    for rule in ("uct", "puct", "none"):
        own = {r.chain: r for r in nodes if r.rule == rule and r.qid == 1}
        assert sum(r.visits for c, r in own.items() if "-" not in c) == 12 == sum(r.visits for c, r in own.items() if "-" in c)
        assert all(r.wins == (r.visits if c == "0-0" else 0) for c, r in own.items() if "-" in c)
        assert all(own[c.split("-")[0]].visits >= r.visits for c, r in own.items())
    first = {r.chain: r.visits for r in nodes if r.rule == "uct" and r.qid == 1 and "-" not in r.chain}
    assert len(first) == 3 and first["0"] == max(first.values())  # all are tried, the winner most


def test_beam_of_full_width_finds_the_largest_reward(spark, policy):
    _, scores = table(spark, lambda a, b: 0)
    score = {r.chain: r.score for r in scores.where("qid = 1").collect()}
    p = chance(policy)
    entropy = {k[2:]: -sum(x * math.log(x) for x in v.values()) for k, v in p.items() if k[1] == 1}
    top = sum(max(entropy[s, 0], entropy[s, 1]) for s in (1, 2))

    def reward(a, b):
        h1 = entropy[1, 0]
        h2 = h1 + entropy[2, int(a > 0)]
        w1, w2 = 1 - h1 / top, 1 - h2 / top
        s1, s2 = score[f"{a}"], score[f"{a}-{b}"]
        mass = w1 + w2
        return s1 + ((w1 * s1 + w2 * s2) / mass if mass > 1e-12 else (s1 + s2) / 2)

    want = sorted(((-reward(a, b), f"{a}-{b}") for a in range(3) for b in range(3)))
    got = bp.beam(policy, scores, 9).where("qid = 1").orderBy("rank").collect()
    assert len(got) == 9 and all(abs(r.reward + w[0]) < 1e-9 for r, w in zip(got, want))


def test_outcomes_of_menus_are_exact(spark, data):
    bank.prepare(spark, data)
    some = [q for q in bank.QUESTIONS if q.qid in (5, 18)]
    rows = bankrun.run_menus(spark, some, most=9).where("slot = slots").collect()
    for q in some:
        options = bankrun.menu(q, 9)
        own = [r for r in rows if r.qid == q.qid]
        assert len(own) == math.prod(map(len, options))
        for r in own:
            picks = [options[k][int(t)] for k, t in enumerate(r.chain.split("-"))]
            text = ch.compose([(n, o.sql) for (n, _), o in zip(q.named, picks)], picks[-1].sql)
            assert r.outcome == ex.outcome(spark, text, q.gold), (q.qid, r.chain)
            assert r.outcome == 1 or any(o.kind for o in picks)


def test_kept_steps_give_the_same_digests(spark, data):
    bank.prepare(spark, data)
    chains = [(q.named, q.close) for q in bank.QUESTIONS if q.qid in (1, 8, 26)] + [([("x", "SELECT 1 AS a, 2 AS a"), ("y", "SELECT 3 AS b FROM x")], "SELECT nope FROM y")]
    fields = ("prefix_key", "depth", "status", "condition", "n_rows", "n_cols", "nulls", "result_key")
    assert sorted(map(str, ex.run_chains(spark, chains).select(*fields).collect())) == sorted(map(str, ex.run_chains(spark, chains, keep=True).select(*fields).collect()))
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("kept_")]


def test_prefixes_that_read_the_same_run_once(spark, data, monkeypatch):
    bank.prepare(spark, data)
    texts, plain = [], ex.run_text
    monkeypatch.setattr(ex, "run_text", lambda spark, text: texts.append(text) or plain(spark, text))
    one = ("one", "SELECT n_nationkey FROM nation")
    chains = [([one, ("two", f"SELECT n_nationkey FROM one WHERE n_nationkey < {k}")], close) for k in (3, 7) for close in ("SELECT count(*) AS n FROM one", "SELECT count(*) AS n FROM two")]
    chains.append(([one, ("two", "SELECT nope FROM one")], "SELECT count(*) AS n FROM one"))
    rows = {r.prefix_key: r for r in ex.run_chains(spark, chains, keep=True).collect()}
    ends = [rows[ex.prefix_keys(*c)[-1]] for c in chains]
    assert len(texts) == 7 and len(rows) == 9  # one, two (twice, and one that fails), one closing query over one, two over two
    assert ends[0].run_key == ends[2].run_key != ends[1].run_key != ends[3].run_key and [r.status for r in ends] == ["ok"] * 4 + ["pruned"]
    values = [plain(spark, ch.compose(*c))["result_key"] for c in chains[:4]]
    assert [r.result_key for r in ends[:4]] == values and len(set(values)) == 3
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("kept_")]


def test_prefixes_of_one_plan_run_once(spark, data, monkeypatch):
    bank.prepare(spark, data)
    texts, plain = [], ex.run_text
    monkeypatch.setattr(ex, "run_text", lambda spark, text, *more: texts.append(text) or plain(spark, text, *more))
    steps = ("SELECT n_nationkey, n_name FROM nation", "SELECT 1 AS extra, n_nationkey, n_name FROM nation")
    chains = [([("one", text)], close) for text in steps for close in ("SELECT count(n_name) AS n FROM one WHERE n_nationkey > 3", "SELECT * FROM one WHERE n_nationkey > 3")]
    rows = {r.prefix_key: r for r in ex.run_chains(spark, chains, keep=True).collect()}
    assert len(texts) == 4 and len(rows) == 6  # the step with and without its constant, one count; SELECT * has another text behind a constant step, so it runs twice
    for steps_, close in chains:
        for k, key in enumerate(ex.prefix_keys(steps_, close)):
            want = plain(spark, ch.compose(steps_, close) if k else ch.compose(steps_, upto=1))
            assert [rows[key][c] for c in ("status", "n_rows", "n_cols", "nulls", "result_key")] == [want[c] for c in ("status", "n_rows", "n_cols", "nulls", "result_key")]
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("kept_")]


def test_chains_hash_the_smaller_side(spark, data):
    bank.prepare(spark, data)
    key, own = "spark.sql.autoBroadcastJoinThreshold", spark.conf.get("spark.sql.adaptive.advisoryPartitionSizeInBytes")
    broadcast = spark.conf.get(key)
    spark.conf.set(key, "-1")
    try:
        with ex.hashing(spark):
            df = spark.sql("SELECT l_quantity, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
            assert len(df.collect()) == spark.table("lineitem").count()
            plan = df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    finally:
        spark.conf.set(key, broadcast)
    assert "ShuffledHashJoin" in plan and "SortMergeJoin" not in plan
    assert spark.conf.get("spark.sql.adaptive.advisoryPartitionSizeInBytes") == own


def test_numbers_of_all_types_have_one_key(spark):
    key = lambda text: digest(spark.sql(text), with_result=True).first().result_key
    assert key("SELECT 0.5D AS a") == key("SELECT 0.5 AS a") == key("SELECT CAST(0.5 AS FLOAT) AS a") == key("SELECT 0.5000004D AS a") != key("SELECT 0.500001D AS a")
    assert key("SELECT -0.0D AS a") == key("SELECT 0.0D AS a") != key("SELECT 0 AS a") and key("SELECT 5.0D AS a") != key("SELECT 5000000 AS a")
    assert key("SELECT 1e12D AS a") == key("SELECT CAST(1000000000000 AS DECIMAL(20,2)) AS a") != key("SELECT 1000000000000.01D AS a")
    assert len({key(f"SELECT CAST({x} AS DOUBLE) AS a") for x in ("'NaN'", "'Infinity'", "'-Infinity'", "NULL", "4.5e9", "4.6e9")}) == 6


def test_values_of_one_text_have_one_key(spark):
    """Whole numbers are hashed as such and texts as texts, in any place, and a null is neither; a digest formats no number that it can count."""
    df = spark.sql("SELECT 1 AS a, 'x' AS b, 0.5D AS c")
    assert "format_number" not in " ".join(digest_module._cells(df.select("a", "b"), 6))
    key = lambda text: digest(spark.sql(text), with_result=True).first().result_key
    assert key("SELECT 5 AS a") == key("SELECT 5L AS a") == key("SELECT '5' AS a") != key("SELECT '05' AS a")
    assert len({key(f"SELECT {x} AS a, {y} AS b") for x, y in (("NULL", "5"), ("5", "NULL"), ("0", "5"), ("'NULL'", "5"), ("'-0'", "5"), ("' 0'", "5"), ("NULL", "NULL"))}) == 7
    assert key("SELECT CAST(NULL AS DOUBLE) AS a") == key("SELECT CAST(NULL AS STRING) AS a")
    row = digest(spark.sql("SELECT 'x' AS b, 2.5D AS c"), with_result=True, leads=(1, 7)).first()
    assert list(row.lead_keys) == [key(f"SELECT {x} AS a, 'x' AS b, 2.5D AS c") for x in (1, 7)]
    # just under and over the middle of two counts, where exact decimals decide
    assert len({key(f"SELECT {x}D AS a") for x in ("0.00000149", "0.0000014", "0.0000011")}) == 1 != len({key(f"SELECT {x}D AS a") for x in ("0.00000149", "0.00000151")})


def test_distinct_counts_of_a_star_run_apart(spark, data):
    bank.prepare(spark, data)
    gold = next(q.gold for q in bank.QUESTIONS if q.qid == 26)
    text = ex.apart(spark, gold)
    assert "UNION ALL" in text and sorted(spark.sql(text).collect()) == sorted(spark.sql(gold).collect())
    for name, rows in (("hub_t", "(1, 'a'), (2, 'a'), (3, 'b'), (4, NULL), (NULL, 'c')"), ("left_t", "(1, 1), (1, 1), (1, NULL), (2, 3), (4, 7), (9, 1), (NULL, 5)"), ("right_t", "(1, 8), (2, 8), (2, 9), (3, 4), (4, NULL)")):
        spark.sql(f"SELECT * FROM VALUES {rows}").toDF(f"{name[0]}_key", f"{name[0]}_value").createOrReplaceTempView(name)
    star = "FROM hub_t JOIN left_t ON l_key = h_key JOIN right_t ON h_key = r_key GROUP BY"
    plain = f"SELECT h_value, count(DISTINCT l_value) AS a, count(DISTINCT r_value) + 1 AS b {star} h_value"
    assert ex.apart(spark, plain) != plain and sorted(map(str, spark.sql(ex.apart(spark, plain)).collect())) == sorted(map(str, spark.sql(plain).collect()))
    for out, by in (("h_value, count(DISTINCT l_value), count(*)", "h_value"), ("l_value, count(DISTINCT l_value), count(DISTINCT r_value)", "l_value"), ("h_value, count(DISTINCT l_value)", "h_value"), ("h_value, sum(l_value), count(DISTINCT r_value)", "h_value")):
        assert ex.apart(spark, f"SELECT {out} {star} {by}") == f"SELECT {out} {star} {by}"  # pairs count here
    assert ex.apart(spark, "WITH left_u AS (SELECT * FROM left_t) " + plain.replace("left_t", "left_u")).count("UNION") == 0


def test_menus_read_small_tables_in_many_tasks(spark, data):
    bank.prepare(spark, data)
    own, rows = spark.table("customer").inputFiles(), spark.table("customer").orderBy("c_custkey").collect()
    with tables.dealt(spark, least=1):
        held = spark.table("customer")
        assert held.rdd.getNumPartitions() == spark.sparkContext.defaultParallelism > len(own) and held.orderBy("c_custkey").collect() == rows
    assert spark.table("customer").inputFiles() == own
    order = bankrun.heaviest_first(spark, bank.QUESTIONS)
    assert sorted(order) == [q.qid for q in bank.QUESTIONS] and 22 in order[:6] and order.index(27) < order.index(23)


def test_ordered_outcome_keeps_the_order(spark, data):
    bank.prepare(spark, data)
    up, down = "SELECT o_orderkey FROM orders ORDER BY o_orderkey", "SELECT o_orderkey FROM orders ORDER BY o_orderkey DESC"
    assert ex.outcome(spark, up, up, "ordered") == 1 and ex.outcome(spark, up, down, "ordered") == 0 and ex.outcome(spark, up, down) == 1
    assert [r.at for r in ex.numbered(spark.sql(up)).orderBy("o_orderkey").collect()] == list(range(spark.table("orders").count()))


def test_digest_parts(spark):
    df = spark.createDataFrame([(1, "a"), (1, None), (2, "b"), (1, "c")], "k int, v string")
    row = digest(df, ("k",), sample=2, with_result=True).first()
    assert (row.n_rows, row.n_cols, row.nulls, row["keys"], row.repeats, row.fanout) == (4, 2, 0.125, 2, 2.0, 2) and len(row.sample) == 2
    empty = digest(df.limit(0), ("k",)).first()
    assert (empty.n_rows, empty.nulls, empty["keys"], empty.fanout) == (0, None, 0, 0)


def test_names_are_repaired_with_their_references(spark, data):
    bank.prepare(spark, data)
    chain = [
        ("a", "SELECT n_nationkey, n_regionkey FROM nation", "step"), ("A", "SELECT n_regionkey FROM a WHERE n_nationkey < 10", "step"), ("a_2", "SELECT a.n_regionkey FROM A", "step"),
        ("a", "SELECT x.n_regionkey FROM a x JOIN a_2 ON x.n_regionkey = a_2.n_regionkey", "step"), ("answer", "SELECT count(*) AS n FROM a", "close"),
    ]
    steps = spark.createDataFrame([(1, 1, k, n, "", s, kind) for k, (n, s, kind) in enumerate(chain, 1)], "qid int, traj_id int, no int, name string, rationale string, sql string, kind string")
    fixed = ch.resolve_names(steps).orderBy("no").collect()
    assert [r.name for r in fixed] == ["a", "A_3", "a_2", "a_4", "answer"]
    text = ch.compose([(r.name, r.sql) for r in fixed if r.kind == "step"], fixed[-1].sql)
    regions = [r.n_regionkey for r in spark.sql("SELECT n_regionkey FROM nation WHERE n_nationkey < 10").collect()]
    assert spark.sql(text).first().n == sum(c * c for c in Counter(regions).values())


def test_redundancy_rules(spark):
    rows = [
        (1, "x", 1, 5, "a", "SELECT * FROM t WHERE k > 1", "ok", 10, 2, "r1"), (1, "x", 2, 5, "b", "SELECT * FROM a WHERE k > 1", "ok", 10, 2, "r1"),
        (1, "x", 3, 5, "c", "SELECT * FROM b JOIN u ON k = j", "ok", 10, 3, "r3"), (1, "x", 4, 5, "d", "SELECT j FROM b JOIN u ON k = j", "ok", 10, 1, "r4"),
        (1, "x", 5, 5, "answer", "SELECT * FROM c", "ok", 10, 3, "r3"),
        (2, "y", 1, 3, "a", "SELECT k FROM t", "ok", 9, 1, "r1"), (2, "y", 2, 3, "b", "SELECT k FROM a", "ok", 9, 1, "r2"), (2, "y", 3, 3, "answer", "SELECT count(*) FROM b", "ok", 1, 1, "r3"),
    ]
    got = {(r.qid, r.slot): {k for k in ("repeats_result", "duplicate_join", "idle_filter", "unreferenced", "keeps_all_rows") if r[k]} for r in ch.redundant_steps(
        spark.createDataFrame(rows, "qid bigint, whole string, slot int, slots int, name string, sql string, status string, n_rows bigint, n_cols int, result_key string")).collect()}
    assert got == {(1, 1): set(), (1, 2): {"repeats_result", "idle_filter"}, (1, 3): set(), (1, 4): {"duplicate_join", "unreferenced"}, (1, 5): set(), (2, 1): set(), (2, 2): {"keeps_all_rows"}, (2, 3): set()}


def test_rewritten_queries_give_gold(spark, data):
    rows = QUERIES["decompose_bank"](spark, data).collect()
    assert len(rows) == 36 and all(r.outcome == 1 for r in rows) and sum(r.n_steps > 1 for r in rows) > 18


def test_labels_equal_plain_rates(spark, data):
    done = xp.runs(spark, data).where("slot = slots").select("qid", "chain", "outcome").collect()
    right = {(r.qid, r.chain): r.outcome for r in done}
    whole = xp.rollouts(spark, data).groupBy("qid", "cand").agg(F.max_by("chain", "step_no").alias("chain")).collect()
    want = defaultdict(list)
    for r in whole:
        parts = r.chain.split("-")
        for k in range(1, len(parts) + 1):
            want[r.qid, "-".join(parts[:k])].append(right[r.qid, r.chain])
    got = {(r.qid, r.chain): (r.visits, r.sigma) for r in bp.prefix_labels(xp.rollouts(spark, data), xp.runs(spark, data)).collect()}
    assert got.keys() == want.keys() and all(got[k][0] == len(v) and abs(got[k][1] - sum(v) / len(v)) < 1e-12 for k, v in want.items())


def test_every_rule_stays_between_one_sample_and_the_bound(spark, data):
    rows = {(r.method, r.n): r.accuracy for r in QUERIES["rl_selection"](spark, data).collect()}
    for n in xp.BUDGETS:
        assert all(rows[m, n] <= rows["pass@n", n] + 1e-9 for m, _ in xp.RULES)
    assert all(rows["pass@n", a] <= rows["pass@n", b] for a, b in zip(xp.BUDGETS, xp.BUDGETS[1:]))
    assert rows["step reward", 8] > rows["self-consistency", 8] > rows["step reward", 1] and rows["step reward", 8] > rows["outcome model", 8]
    assert all(rows[m, 1] == rows["step reward", 1] for m, _ in xp.RULES)


def test_formats_and_errors(spark, data):
    f = {(r.format, r.split): r.accuracy for r in QUERIES["bank_variants"](spark, data).collect()}
    assert f["chain", "(all)"] > f["rationale only", "(all)"] > f["direct", "(all)"]
    all_ = {r.error_type: r for r in QUERIES["bank_error_delta"](spark, data).collect()}["(all)"]
    assert all_.after < all_.before
    shares = QUERIES["bank_errors"](spark, data).collect()
    assert all(r.errors <= next(s.errors for s in shares if (s.method, s.grp, s.error_type) == (r.method, "(all)", "(all)")) for r in shares)


def test_gold_chains_are_right(spark, data):
    rows = QUERIES["candidate_outcomes"](spark, data).collect()
    assert {r.qid for r in rows if r.slips == 0 and r.outcome == 1} == set(range(1, 37))
    assert any(r.error_type == bankrun.NEEDLESS and r.outcome == 1 for r in rows)


def test_every_method_is_trained_with_every_seed():
    assert sorted(xp.RUNS_OF) == sorted(f"{m}|{s}" for m in ("step reward", "outcome only", "graded outcome") for s in (17, 18, 19))


def test_stability_is_that_of_all_rounds(spark, data):
    curve = QUERIES["rl_training"](spark, data).where("split = 'train' and protocol = 'sampled'").collect()
    held = defaultdict(dict)
    for r in curve:
        held[f"{r.method}|{r.seed}"][r.round] = r.accuracy
    rounds, warm_up = TrainConfig().rounds, TrainConfig().warm_up
    assert len(curve) == len(xp.RUNS_OF) * (rounds + 1) and all(sorted(v) == list(range(rounds + 1)) for v in held.values())
    rows = {r.method: r for r in QUERIES["bank_stability"](spark, data).collect()}
    assert rows.keys() == held.keys() == set(xp.RUNS_OF)
    for name, v in held.items():
        late = [v[k] for k in range(warm_up + 1, rounds + 1)]
        off = max((k for k in v if abs(v[k] - v[rounds]) > 2.0), default=0)
        assert abs(rows[name].mean - np.mean(late)) < 1e-9 and abs(rows[name].std - np.std(late, ddof=1)) < 1e-9
        assert (rows[name].last, rows[name].peak, rows[name].converged) == (v[rounds], max(v.values()), off + 1)
