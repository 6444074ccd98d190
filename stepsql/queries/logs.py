"""Token logs, policies, prefix trees, chain texts and score-model inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stepsql.functions.entropy import entropy_bounds
from stepsql.functions.entropy import token_entropy as entropy_of
from stepsql.operators import advantage as adv
from stepsql.operators import chains as ch
from stepsql.operators import digest as dg
from stepsql.operators import labels as mc
from stepsql.operators import measures as ms
from stepsql.operators import policy as pol
from stepsql.operators import reward as rw
from stepsql.sources.carriers import LINE_ORDER, document_lines, event_tokens, page_tags, trail_events, trail_orders, turn_steps
from stepsql.sources.tables import spread, table

from .carrier_sql import EVENTS, LINES, ORDERS, TOKENS, rewards
from .core import r6
from .registry import query

# --- policies ----------------------------------------------------------------------------------


@query(f"WITH {TOKENS} SELECT prev, token, n, round(p, 6) + 0.0 AS p FROM policy")
def bigram_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(pol.fit_policy(event_tokens(spark, sf_dir)))


@query(f"WITH {TOKENS}, v AS (SELECT count(DISTINCT token) AS v FROM pairs) SELECT prev, token, n, round((n + 1) / (sum(n) OVER (PARTITION BY prev) + v), 6) + 0.0 AS p FROM pairs, v")
def bigram_policy_smoothed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(pol.fit_policy(event_tokens(spark, sf_dir), alpha=1.0))


@query("WITH t AS (SELECT (conv_id % 10) AS qid, conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS s, string_split(text, ' ') AS w FROM conversations), k AS (SELECT conv_id, s, unnest(w) AS token, unnest(list_prepend('^', w[1:len(w) - 1])) AS prev FROM t), p AS (SELECT prev, token, count(*) AS n FROM k GROUP BY ALL), q AS (SELECT *, n / sum(n) OVER (PARTITION BY prev) AS p FROM p) SELECT count(*) AS tokens, round(sum(-ln(p)), 4) + 0.0 AS loss, round(avg(-ln(p)), 6) + 0.0 AS mean_loss FROM k JOIN q USING (prev, token)")
def sft_nll(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequence loss of conversation words under the bigram policy fitted to them."""
    tokens = conversation_tokens(spark, sf_dir)
    got = pol.nll(tokens, pol.fit_policy(tokens))
    return got.select("tokens", (F.round("loss", 4) + 0.0).alias("loss"), (F.round("mean_loss", 6) + 0.0).alias("mean_loss"))


@query("WITH t AS (SELECT conv_id, role, string_split(text, ' ') AS w FROM conversations), k AS (SELECT role, unnest(w) AS token FROM t), p AS (SELECT token, count(*) AS n FROM k GROUP BY ALL), q AS (SELECT token, n / sum(n) OVER () AS p FROM p) SELECT role, count(*) AS tokens, round(avg(-ln(p)), 6) + 0.0 AS mean_loss FROM k JOIN q USING (token) GROUP BY role")
def sft_nll_masked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The loss of each role's words alone, under one unigram policy: masks for rationale-like and step-like parts."""
    tokens = table(spark, sf_dir, "conversations").select("role", F.explode(F.split("text", " ")).alias("token"))
    policy = pol.fit_policy(tokens, ()).select("token", "p")
    joined = tokens.join(policy, "token")
    return r6(joined.groupBy("role").agg(F.count("*").alias("tokens"), F.avg(-F.ln("p")).alias("mean_loss")))


def conversation_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = turn_steps(spark, sf_dir).select("qid", "traj_id", "step_no", F.split("text", " ").alias("w"))
    return t.select("qid", "traj_id", "step_no", F.posexplode("w").alias("pos", "token"), "w").withColumn(
        "prev", F.when(F.col("pos") == 0, F.lit("^")).otherwise(F.get("w", F.col("pos") - 1))
    ).drop("w")


@query(f"WITH {TOKENS} SELECT prev, token, round(p, 6) + 0.0 AS p FROM policy QUALIFY row_number() OVER (PARTITION BY prev ORDER BY n DESC, token) = 1")
def greedy_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(pol.greedy(pol.fit_policy(event_tokens(spark, sf_dir))))


@query()
def sample_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight sampled chains of five events for every user."""
    users = table(spark, sf_dir, "events").select(F.col("user_id").alias("qid")).distinct()
    return pol.sample_chains(pol.fit_policy(event_tokens(spark, sf_dir)).select("prev", "token", "p"), users, 8, 5)


@query("WITH pages_ AS (SELECT regexp_extract(url, '://([^/]+)', 1) AS qid, page_id, regexp_extract_all(html, '<(/?[a-z][a-z0-9]*)', 1) AS t FROM pages), k AS (SELECT qid, unnest(t) AS token, unnest(list_prepend('^', t[1:len(t) - 1])) AS prev FROM pages_), p AS (SELECT prev, token, count(*) AS n FROM k GROUP BY ALL), q AS (SELECT *, n / sum(n) OVER (PARTITION BY prev) AS p FROM p) SELECT prev, count(*) AS tokens, round(-sum(p * ln(p)), 6) + 0.0 AS entropy FROM q GROUP BY prev")
def tag_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of the next tag after each tag of the pages."""
    own = Window.partitionBy("qid", "traj_id").orderBy("pos")
    tokens = page_tags(spark, sf_dir).withColumn("prev", F.coalesce(F.lag("token").over(own), F.lit("^")))
    p = pol.fit_policy(tokens)
    return r6(p.groupBy("prev").agg(F.count("*").alias("tokens"), (-F.sum(F.col("p") * F.ln("p"))).alias("entropy")))


# --- entropies ---------------------------------------------------------------------------------


@query(f"WITH {TOKENS} SELECT prev, round(entropy, 6) + 0.0 AS entropy FROM entropies")
def token_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of a distribution kept as a map."""
    p = pol.fit_policy(event_tokens(spark, sf_dir))
    dist = p.groupBy("prev").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("token", "p")))).alias("dist"))
    return r6(dist.select("prev", entropy_of(F.col("dist")).alias("entropy")))


@query(f"WITH {TOKENS}, r AS (SELECT prev, p FROM policy QUALIFY row_number() OVER (PARTITION BY prev ORDER BY n DESC, token) <= 2), s AS (SELECT prev, sum(p) AS m, -sum(p * ln(p)) AS h FROM r GROUP BY prev) SELECT prev, round(h - CASE WHEN 1 - m > 0 THEN (1 - m) * ln(1 - m) ELSE 0 END, 6) + 0.0 AS lower, round(h - CASE WHEN 1 - m > 0 THEN (1 - m) * ln(1 - m) - (1 - m) * ln(3) ELSE 0 END, 6) + 0.0 AS upper FROM s")
def entropy_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds from the two likeliest tokens of five."""
    p = pol.fit_policy(event_tokens(spark, sf_dir))
    order = Window.partitionBy("prev").orderBy(F.desc("n"), "token")
    top = p.withColumn("r", F.row_number().over(order)).where("r <= 2").groupBy("prev").agg(F.array_sort(F.collect_list("p")).alias("top"))
    low, high = entropy_bounds(F.col("top"), 5)
    return r6(top.select("prev", low.alias("lower"), high.alias("upper")))


@query(f"WITH {EVENTS} SELECT qid, traj_id, step_no, n_tokens, round(h_step, 6) + 0.0 AS h_step FROM trail")
def step_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(trail_events(spark, sf_dir).select("qid", "traj_id", "step_no", "n_tokens", "h_step"))


# --- ratios, surrogate, divergence ----------------------------------------------------------------


@query(f"WITH {TOKENS} SELECT event_id, round(exp(logp - logp_ref), 6) + 0.0 AS ratio FROM tokens")
def token_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(event_tokens(spark, sf_dir).select("event_id", adv.ratio("ref").alias("ratio")))


_SURROGATE = f"""{rewards(EVENTS, scope="corpus")},
raws AS (SELECT *, outcome + sum(prefix_score) OVER (PARTITION BY qid, traj_id ORDER BY step_no ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS adv_raw FROM rewarded),
moments AS (SELECT qid, avg(adv_raw) AS mean, stddev_pop(adv_raw) AS sd, min(adv_raw) AS lo, max(adv_raw) AS hi FROM raws GROUP BY qid),
advs AS (SELECT r.qid, traj_id, day, CASE WHEN lo = hi THEN 0.0 ELSE (adv_raw - mean) / sd END AS adv
  FROM (SELECT r.*, d.day FROM raws r JOIN (SELECT qid, traj_id, day, row_number() OVER (PARTITION BY qid, traj_id ORDER BY day) AS step_no FROM days) d USING (qid, traj_id, step_no)) r JOIN moments USING (qid)),
terms AS (
  SELECT t.qid, t.traj_id, event_id, adv, exp(logp - logp_ref) AS rho, logp_ref - logp AS d FROM tokens t JOIN advs a ON a.qid = t.qid AND a.traj_id = t.traj_id AND a.day = t.day),
clipped AS (SELECT *, least(rho * adv, least(greatest(rho, 0.8), 1.2) * adv) AS s, exp(d) - d - 1 AS k3 FROM terms)"""


def surrogate_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the standardised advantage of their step (the user's day); the closing query has as many tokens as the last step."""
    from stepsql.config import RewardConfig

    steps = adv.standardise(adv.raw(rw.step_reward(trail_events(spark, sf_dir), RewardConfig(norm_scope="corpus"))))
    own = Window.partitionBy("qid", "traj_id")
    steps = steps.withColumn("final_tokens", F.max(F.struct("step_no", "n_tokens")).over(own).getField("n_tokens"))
    tokens = event_tokens(spark, sf_dir)
    day = F.dense_rank().over(Window.partitionBy("qid", "traj_id").orderBy("day"))
    return tokens.withColumn("step_no", day).join(steps.select("qid", "traj_id", "step_no", "adv", "final_tokens"), ["qid", "traj_id", "step_no"])


@query(f"WITH {_SURROGATE} SELECT event_id, round(s, 5) + 0.0 AS surrogate FROM clipped")
def clipped_surrogate(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = surrogate_tokens(spark, sf_dir)
    return got.select("event_id", (F.round(adv.surrogate(adv.ratio("ref"), F.col("adv")), 5) + 0.0).alias("surrogate"))


@query(f"WITH {_SURROGATE}, y AS (SELECT qid, traj_id, arg_max(n_tokens, step_no) AS y FROM trail GROUP BY ALL), c AS (SELECT qid, traj_id, sum(s) / (count(*) + any_value(y)) AS term, avg(k3) AS kl FROM clipped JOIN y USING (qid, traj_id) GROUP BY ALL) SELECT qid, round(avg(term) - 0.02 * avg(kl), 5) + 0.0 AS loss, round(avg(kl), 5) + 0.0 AS kl FROM c GROUP BY qid")
def group_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = adv.group_loss(surrogate_tokens(spark, sf_dir), final_tokens="final_tokens")
    return got.select("qid", (F.round("loss", 5) + 0.0).alias("loss"), (F.round("kl", 5) + 0.0).alias("kl"))


@query(f"WITH {_SURROGATE}, c AS (SELECT qid, traj_id, avg(k3) AS kl FROM clipped GROUP BY ALL), l AS (SELECT qid, traj_id, max_by(reward, step_no) AS reward, max(outcome) AS outcome FROM rewarded GROUP BY ALL) SELECT round(avg(reward + outcome - 0.02 * kl), 5) + 0.0 AS objective, count(*) AS chains FROM l JOIN c USING (qid, traj_id)")
def rl_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stepsql.config import RewardConfig

    rewarded = rw.trajectory_reward(rw.step_reward(trail_events(spark, sf_dir), RewardConfig(norm_scope="corpus")))
    kl = event_tokens(spark, sf_dir).groupBy("qid", "traj_id").agg(F.avg(adv.kl("k3")).alias("kl"))
    got = adv.objective(rewarded, kl)
    return got.select((F.round("objective", 5) + 0.0).alias("objective"), "chains")


@query(f"WITH {TOKENS} SELECT qid, round(avg(logp - logp_ref), 6) + 0.0 AS k1, round(avg((logp_ref - logp) ** 2 / 2), 6) + 0.0 AS k2, round(avg(exp(logp_ref - logp) - (logp_ref - logp) - 1), 6) + 0.0 AS k3 FROM tokens GROUP BY qid")
def kl_k3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All three estimators by user."""
    t = event_tokens(spark, sf_dir)
    return r6(t.groupBy("qid").agg(*[F.avg(adv.kl(k)).alias(k) for k in ("k1", "k2", "k3")]))


@query(f"WITH {TOKENS} SELECT prev, round(sum(p * ln(p / q)), 6) + 0.0 AS kl FROM policy JOIN reference USING (token) GROUP BY prev")
def kl_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = event_tokens(spark, sf_dir)
    return r6(pol.exact_kl(pol.fit_policy(t), pol.fit_policy(t, ())))


@query(f"""WITH {rewards(EVENTS, scope="corpus")},
l AS (SELECT qid, traj_id, round(max_by(reward, step_no), 9) AS reward FROM rewarded GROUP BY ALL),
p AS (SELECT qid, traj_id, sum(logp - logp_ref) AS d FROM tokens GROUP BY ALL),
b AS (SELECT qid, arg_max(d, (reward, traj_id)) AS x, arg_min(d, (reward, traj_id)) AS y, count(*) AS n FROM l JOIN p USING (qid, traj_id) GROUP BY qid)
SELECT qid, round(ln(1 + exp(-0.1 * (x - y))), 6) + 0.0 AS loss FROM b WHERE n > 1""")
def pair_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Preference baseline: best against worst week of each user."""
    from stepsql.config import RewardConfig

    rewarded = rw.trajectory_reward(rw.step_reward(trail_events(spark, sf_dir), RewardConfig(norm_scope="corpus"))).withColumn("reward", F.round("reward", 9))
    logs = event_tokens(spark, sf_dir).groupBy("qid", "traj_id").agg(F.sum("logp").alias("logp"), F.sum("logp_ref").alias("logp_ref"))
    return r6(adv.pair_loss(rewarded.join(logs, ["qid", "traj_id"])))


# --- prefix trees ------------------------------------------------------------------------------


_WORDS = ", ".join(f"sum(('0x' || substr(h, {8 * i + 1}, 8))::BIGINT) OVER chain" for i in range(4))


@query(f"""WITH {LINES}, s AS (SELECT qid, traj_id, outcome, unnest(range(len(steps))) AS place, unnest(steps) AS step FROM completions),
h AS (SELECT *, md5(place || chr(31) || step) AS h FROM s),
k AS (SELECT *, md5(concat_ws('-', {_WORDS})) AS node FROM h WINDOW chain AS (PARTITION BY qid, traj_id ORDER BY place ROWS UNBOUNDED PRECEDING))
SELECT qid, (place + 1)::INTEGER AS depth, node, count(*) AS visits, sum(outcome)::BIGINT AS wins FROM k GROUP BY ALL""")
def prefix_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes of the tree of document lines, named by running digests that SQL can form too."""
    return mc.prefix_tree(document_lines(spark, sf_dir)).select("qid", "depth", F.col("prefix_key").alias("node"), "visits", "wins")


@query(f"WITH {LINES}, n AS (SELECT qid, prefix, depth, count(*) AS v, sum(outcome) AS w, avg(outcome) AS s FROM visits GROUP BY ALL) SELECT qid, depth::INTEGER AS depth, count(*) AS nodes, sum(v)::BIGINT AS visits, sum(w)::BIGINT AS wins, count(*) FILTER (v > 1) AS shared, count(*) FILTER (s > 0 AND s < 1) AS mixed, round(avg(s), 6) + 0.0 AS mean_sigma FROM n GROUP BY ALL")
def mc_sigma(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Success labels by depth, from chained digests."""
    n = mc.prefix_tree(document_lines(spark, sf_dir))
    return r6(
        n.groupBy("qid", "depth").agg(
            F.count("*").alias("nodes"), F.sum("visits").alias("visits"), F.sum("wins").alias("wins"), F.count_if(F.col("visits") > 1).alias("shared"),
            F.count_if((F.col("sigma") > 0) & (F.col("sigma") < 1)).alias("mixed"), F.avg("sigma").alias("mean_sigma"),
        )
    )


@query(f"""WITH {LINES}, l AS (SELECT *, -len(array_to_string(steps, chr(31))) / 1000.0 AS lp FROM completions),
p AS (SELECT qid, lp, outcome, steps, array_to_string(steps, chr(31)) AS whole, unnest(range(1, len(steps) + 1)) AS depth FROM l),
o AS (SELECT qid, array_to_string(steps[1:depth], chr(31)) AS prefix, whole, max(lp) AS lp, max(outcome) AS r FROM p GROUP BY ALL),
s AS (SELECT qid, prefix, sum(exp(lp) * r) / sum(exp(lp)) AS sigma FROM o GROUP BY ALL)
SELECT qid, count(*) AS nodes, round(avg(sigma), 6) + 0.0 AS mean_sigma FROM s GROUP BY qid""")
def mc_sigma_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Success under completion probabilities; a completion's log-probability falls with its length."""
    lines = document_lines(spark, sf_dir).withColumn("logp", -F.length(F.array_join("steps", "\x1f")) / 1000.0)
    return r6(mc.weighted_sigma(lines).groupBy("qid").agg(F.count("*").alias("nodes"), F.avg("sigma").alias("mean_sigma")))


@query(f"WITH {LINES} SELECT qid, count(*) AS completions, count(DISTINCT array_to_string(steps, chr(31))) AS paths, round(1 - count(DISTINCT array_to_string(steps, chr(31))) / count(*), 6) + 0.0 AS duplicate_share FROM completions GROUP BY qid")
def path_diversity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(mc.path_diversity(document_lines(spark, sf_dir)))


# --- score model -------------------------------------------------------------------------------


@query(f"WITH {ORDERS} SELECT qid, traj_id, string_agg('step ' || step_no || ' tokens ' || n_tokens || ' <step>', ' ' ORDER BY step_no) AS input FROM trail GROUP BY ALL")
def scorer_input(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fragments and their results, a marker after each."""
    steps = rw.nest(trail_orders(spark, sf_dir))
    return steps.select("qid", "traj_id", F.array_join(F.transform("steps", lambda s: F.concat(F.lit("step "), s["step_no"].cast("string"), F.lit(" tokens "), s["n_tokens"].cast("string"), F.lit(" <step>"))), " ").alias("input"))


@query(f"WITH {ORDERS} SELECT qid, traj_id, step_no, n_tokens, coalesce(n_tokens - lag(n_tokens) OVER w, 0)::INTEGER AS growth, round(avg(score) OVER (w ROWS UNBOUNDED PRECEDING), 6) + 0.0 AS mean_score, outcome FROM trail WINDOW w AS (PARTITION BY qid, traj_id ORDER BY step_no)")
def scorer_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("qid", "traj_id").orderBy("step_no")
    t = trail_orders(spark, sf_dir)
    return r6(t.select("qid", "traj_id", "step_no", "n_tokens", F.coalesce(F.col("n_tokens") - F.lag("n_tokens").over(w), F.lit(0)).alias("growth"), F.avg("score").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("mean_score"), "outcome"))


@query(f"WITH {ORDERS}, s AS (SELECT greatest(1e-6, least(1 - 1e-6, score)) AS s, outcome AS y FROM trail) SELECT count(*) AS rows, round(sum(-(y * ln(s) + (1 - y) * ln(1 - s))), 3) + 0.0 AS loss, round(avg(-(y * ln(s) + (1 - y) * ln(1 - s))), 6) + 0.0 AS mean_loss FROM s")
def prm_bce(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = ms.bce(trail_orders(spark, sf_dir), "outcome")
    return got.select("rows", (F.round("loss", 3) + 0.0).alias("loss"), (F.round("mean_loss", 6) + 0.0).alias("mean_loss"))


@query(f"WITH {ORDERS}, t AS (SELECT round(score, 6) AS score, outcome FROM trail) SELECT least(floor(score * 10), 9)::INTEGER AS bin, count(*) AS rows, round(avg(score), 6) + 0.0 AS mean_score, round(avg(outcome), 6) + 0.0 AS mean_outcome FROM t GROUP BY ALL")
def score_calibration(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(ms.calibration(trail_orders(spark, sf_dir).withColumn("score", F.round("score", 6))))


# --- digests, chains -----------------------------------------------------------------------------


@query("SELECT count(*) AS n_rows, 11 AS n_cols, 0.0::DOUBLE AS nulls, count(DISTINCT (l_orderkey, l_linenumber)) AS keys, round(count(*) / count(DISTINCT (l_orderkey, l_linenumber)), 6) + 0.0 AS repeats, (SELECT max(k) - 1 FROM (SELECT count(*) AS k FROM lineitem GROUP BY l_orderkey, l_linenumber)) AS fanout FROM lineitem")
def digest_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(dg.digest(table(spark, sf_dir, "lineitem"), ("l_orderkey", "l_linenumber")))


@query("SELECT o_custkey, b AS rows_before, a AS rows_after, round(a / b, 6) + 0.0 AS ratio FROM (SELECT o_custkey, count(*) AS b FROM orders GROUP BY ALL) JOIN (SELECT o_custkey, count(*) AS a FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL) USING (o_custkey) WHERE a > b")
def fanout_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers whose orders the line-item join multiplies."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    after = orders.join(table(spark, sf_dir, "lineitem").select("l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    return r6(dg.fanout(orders, after, ["o_custkey"]))


def text_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Step texts for the bulk chain tools: one chain an order; the text of a step refers to the step before it, now and
    then to one that does not exist, and names repeat by rule."""
    o = Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER)
    t = table(spark, sf_dir, "lineitem").withColumn("no", F.row_number().over(o))
    last = F.count("*").over(Window.partitionBy("l_orderkey"))
    name = F.concat(F.lit("s"), F.when(F.col("l_partkey") % 17 == 0, F.lit(1)).otherwise(F.col("no")).cast("string"))
    ref = F.when(F.col("no") == 1, F.lit("lineitem")).when(F.col("l_partkey") % 13 == 0, F.lit("missing")).otherwise(F.concat(F.lit("s"), (F.col("no") - 1).cast("string")))
    close = F.when(F.col("l_partkey") % 29 == 0, F.lit("SELECT count(* FROM ")).otherwise(F.lit("SELECT * FROM "))
    return t.withColumn("last", last).select(
        (F.col("l_orderkey") % 100).alias("qid"), F.col("l_orderkey").alias("traj_id"), "no", name.alias("name"),
        F.concat(F.lit("take part "), F.col("l_partkey").cast("string")).alias("rationale"), F.concat(close, ref).alias("sql"),
        F.when((F.col("no") == F.col("last")) & (F.col("last") > 1), F.lit("close")).otherwise(F.lit("step")).alias("kind"),
    )


_TEXTS = f"""
n AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY {", ".join(LINE_ORDER)})::INTEGER AS no FROM lineitem),
m AS (SELECT *, count(*) OVER (PARTITION BY l_orderkey) AS last FROM n),
texts AS (
  SELECT l_orderkey % 100 AS qid, l_orderkey AS traj_id, no, 's' || CASE WHEN l_partkey % 17 = 0 THEN 1 ELSE no END AS name, 'take part ' || l_partkey AS rationale,
    CASE WHEN l_partkey % 29 = 0 THEN 'SELECT count(* FROM ' ELSE 'SELECT * FROM ' END || CASE WHEN no = 1 THEN 'lineitem' WHEN l_partkey % 13 = 0 THEN 'missing' ELSE 's' || (no - 1) END AS sql,
    CASE WHEN no = last AND last > 1 THEN 'close' ELSE 'step' END AS kind FROM m)"""


@query(f"WITH {_TEXTS} SELECT * FROM texts")
def chain_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps gathered into chains and spread again."""
    return ch.steps_from_chains(ch.chains_from_steps(text_steps(spark, sf_dir)))


@query(f"WITH {_TEXTS}, c AS (SELECT qid, traj_id, string_agg(name || ' AS (' || sql || ')', ', ' ORDER BY no) FILTER (kind = 'step') AS s, max(sql) FILTER (kind = 'close') AS q FROM texts GROUP BY ALL) SELECT qid, traj_id, 'WITH ' || s || ' ' || q AS query FROM c")
def compose_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ch.compose_column(ch.chains_from_steps(text_steps(spark, sf_dir)))


@query(f"""WITH {_TEXTS},
bad AS (SELECT qid, traj_id, count(*) FILTER (sql LIKE '%count(* FROM%') AS malformed FROM texts GROUP BY ALL),
named AS (SELECT qid, traj_id, name, count(*) AS k, min(no) AS since FROM texts WHERE kind = 'step' GROUP BY ALL),
conf AS (SELECT qid, traj_id, sum(k - 1)::BIGINT AS conflicts FROM named GROUP BY ALL),
refs AS (SELECT qid, traj_id, no, regexp_extract(sql, 'FROM ([a-z0-9_]+)', 1) AS name FROM texts),
und AS (SELECT qid, traj_id, count(*) AS undefined FROM refs r LEFT JOIN named n USING (qid, traj_id, name) WHERE name <> 'lineitem' AND (since IS NULL OR since >= no) GROUP BY ALL)
SELECT qid, traj_id, malformed, coalesce(undefined, 0)::BIGINT AS undefined, coalesce(conflicts, 0)::BIGINT AS conflicts FROM bad LEFT JOIN und USING (qid, traj_id) LEFT JOIN conf USING (qid, traj_id)""")
def validate_bulk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ch.validate_bulk(text_steps(spark, sf_dir), ["lineitem"])


@query(f"""WITH {_TEXTS},
k AS (SELECT *, row_number() OVER (PARTITION BY qid, traj_id, kind = 'step', name ORDER BY no) AS k FROM texts),
names AS (SELECT qid, traj_id, list(name) AS taken FROM texts WHERE kind = 'step' GROUP BY ALL),
own AS (SELECT qid, traj_id, no, name, CASE WHEN k = 1 THEN name ELSE name || '_' || list_filter(range(2, k + len(taken) + 1), lambda i: NOT list_contains(taken, name || '_' || i))[k - 1] END AS new FROM k JOIN names USING (qid, traj_id) WHERE kind = 'step'),
refs AS (SELECT t.qid, t.traj_id, t.no, arg_max(o.new, o.no) AS new, any_value(o.name) AS old FROM texts t JOIN own o ON o.qid = t.qid AND o.traj_id = t.traj_id AND o.no < t.no AND o.name = regexp_extract(t.sql, 'FROM ([a-z0-9_]+)$', 1) GROUP BY ALL)
SELECT t.qid, t.traj_id, t.no, CASE WHEN kind = 'step' THEN o.new ELSE t.name END AS name, CASE WHEN r.new <> r.old THEN regexp_replace(t.sql, 'FROM .*$', 'FROM ' || r.new || ' AS ' || r.old) ELSE t.sql END AS sql
FROM texts t LEFT JOIN own o ON t.kind = 'step' AND o.qid = t.qid AND o.traj_id = t.traj_id AND o.no = t.no LEFT JOIN refs r ON r.qid = t.qid AND r.traj_id = t.traj_id AND r.no = t.no""")
def resolve_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated names renamed and later references led to the latest step of the name."""
    return ch.resolve_names(text_steps(spark, sf_dir)).select("qid", "traj_id", "no", "name", "sql")


@query(f"WITH {_TEXTS}, c AS (SELECT qid, traj_id, count(*) FILTER (kind = 'step') AS k, sum(len(string_split(rationale, ' '))) AS r, sum(len(string_split(sql, ' '))) AS s, count(*) AS n FROM texts GROUP BY ALL) SELECT count(*) AS chains, round(100 * count(*) / (SELECT count(*) FROM orders), 6) + 0.0 AS acceptance, round(avg(k), 6) + 0.0 AS mean_steps, max(k) AS max_steps, round(sum(r) / sum(n), 6) + 0.0 AS rationale_words, round(sum(s) / sum(n), 6) + 0.0 AS step_words FROM c")
def corpus_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(ch.corpus_stats(text_steps(spark, sf_dir), table(spark, sf_dir, "orders")))


_DIGESTS = f"""
n AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY {", ".join(LINE_ORDER)})::INTEGER AS no FROM lineitem),
d AS (SELECT l_orderkey % 100 AS qid, l_orderkey AS traj_id, no, l_quantity::INTEGER AS n_rows, (l_partkey % 7)::VARCHAR AS result_key, 0.05 + l_tax AS h_step FROM n),
f AS (SELECT *, row_number() OVER (PARTITION BY qid, traj_id, result_key ORDER BY no) > 1 AS repeats_result, coalesce(n_rows = lag(n_rows) OVER (PARTITION BY qid, traj_id ORDER BY no), false) AS keeps_all_rows FROM d)"""


def digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items read as step digests: quantity as row count, part class as result."""
    o = Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER)
    t = table(spark, sf_dir, "lineitem").withColumn("no", F.row_number().over(o))
    return t.select((F.col("l_orderkey") % 100).alias("qid"), F.col("l_orderkey").alias("traj_id"), "no", F.col("l_quantity").cast("int").alias("n_rows"), (F.col("l_partkey") % 7).cast("string").alias("result_key"), (0.05 + F.col("l_tax")).alias("h_step"))


@query(f"WITH {_DIGESTS} SELECT qid, traj_id, no, repeats_result, keeps_all_rows, repeats_result OR keeps_all_rows AS redundant FROM f")
def redundancy_flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ch.redundancy(digests(spark, sf_dir)).select("qid", "traj_id", "no", "repeats_result", "keeps_all_rows", "redundant")


_SAMPLED = "s AS (SELECT traj_id FROM (SELECT DISTINCT traj_id FROM d) ORDER BY md5(traj_id || '-17'), traj_id LIMIT 500)"


def sampled_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = digests(spark, sf_dir).select("traj_id").distinct()
    return ids.orderBy(F.md5(F.concat(F.col("traj_id").cast("string"), F.lit("-17"))), "traj_id").limit(500)


@query(f"WITH {_DIGESTS}, {_SAMPLED} SELECT traj_id FROM s")
def sample_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """500 chains by digest order: the same on every engine."""
    return sampled_chains(spark, sf_dir)


@query(f"""WITH {_DIGESTS}, {_SAMPLED},
c AS (SELECT traj_id, bool_or(repeats_result OR keeps_all_rows) AS redundant, avg(h_step) AS h FROM f JOIN s USING (traj_id) GROUP BY traj_id),
t AS (SELECT max(h) AS top FROM c)
SELECT redundant, count(*) AS chains, round(avg(h), 6) + 0.0 AS mean_entropy, round(avg(1 - h / top), 6) + 0.0 AS mean_weight FROM c, t GROUP BY redundant""")
def redundancy_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy and weight of sampled chains with and without redundant steps, under one shared normaliser."""
    d = ch.redundancy(digests(spark, sf_dir)).join(sampled_chains(spark, sf_dir), "traj_id")
    c = d.groupBy("traj_id").agg(F.bool_or("redundant").alias("redundant"), F.avg("h_step").alias("h"))
    top = c.agg(F.max("h").alias("top"))
    both = c.crossJoin(F.broadcast(top))  # one row
    return r6(both.groupBy("redundant").agg(F.count("*").alias("chains"), F.avg("h").alias("mean_entropy"), F.avg(1 - F.col("h") / F.col("top")).alias("mean_weight")))


@query(f"""WITH {_DIGESTS}, c AS (SELECT qid, traj_id, max(n_rows) AS gold, min(n_rows) AS kept, count(*) AS n, count(*) FILTER (repeats_result) AS r FROM f GROUP BY ALL)
SELECT CASE WHEN kept * 4 < gold THEN 'data loss' WHEN r > 0 THEN 'redundant step' WHEN n >= 9 THEN 'wrong boundary' ELSE 'not step-related' END AS category, count(*) AS chains FROM c GROUP BY ALL""")
def chain_error_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Step-level audit of chains by rule."""
    d = ch.redundancy(digests(spark, sf_dir)).groupBy("qid", "traj_id").agg(
        F.max("n_rows").alias("gold_rows"), (4 * F.min("n_rows")).alias("kept_rows"), F.count("*").alias("n_steps"), F.count_if("repeats_result").alias("redundant_steps")
    )
    return ch.chain_error(d.withColumn("merged_steps", (F.col("n_steps") >= 9).cast("int"))).groupBy("category").agg(F.count("*").alias("chains"))


@query(f"WITH {_DIGESTS}, r AS (SELECT traj_id, result_key, n_rows FROM d WHERE no = 1), g AS (SELECT traj_id, result_key, n_rows FROM d WHERE no = 2) SELECT traj_id, (r.result_key = g.result_key)::INTEGER AS outcome FROM r JOIN g USING (traj_id)")
def outcome_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcome of predictions against gold results, by result key."""
    d = digests(spark, sf_dir)
    p, g = d.where("no = 1").select("traj_id", F.col("result_key").alias("p")), d.where("no = 2").select("traj_id", F.col("result_key").alias("g"))
    return p.join(g, "traj_id").select("traj_id", (F.col("p") == F.col("g")).cast("int").alias("outcome"))


@query("""WITH b AS (SELECT item_id, list_filter(string_split(lower(text), ' '), lambda x: x <> '') AS w FROM benchmark),
g AS (SELECT DISTINCT item_id, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT item_id, w, unnest(range(1, len(w) - 6)) AS i FROM b)),
d AS (SELECT doc_id, list_filter(string_split(lower(text), ' '), lambda x: x <> '') AS w FROM documents),
h AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM d))
SELECT item_id, count(DISTINCT doc_id) AS documents, count(DISTINCT g) AS shared FROM g JOIN h USING (g) GROUP BY item_id""")
def leak_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items whose runs of eight words stand in documents. Runs meet by hash and are then compared as words. The items'
    runs are broadcast up to a counted bound; beyond it both sides are dealt out by hash."""

    def runs(df: DataFrame, key: str, with_run: bool) -> DataFrame:
        w = df.select(key, F.filter(F.split(F.lower("text"), " "), lambda x: x != "").alias("w")).where(F.size("w") >= 8)
        hashed = w.select(key, F.transform("w", lambda x: F.xxhash64(x)).alias("k"), *(["w"] if with_run else []))
        at = F.transform(F.sequence(F.lit(0), F.size("k") - 8), lambda i: F.struct(i.alias("i"), F.xxhash64(*[F.get("k", i + j) for j in range(8)]).alias("h"), *([run("w", i).alias("run")] if with_run else [])))
        return hashed.select(key, F.inline(at))

    run = lambda w, i: F.slice(w, i + 1, F.lit(8))
    words = lambda: F.filter(F.split(F.lower("text"), " "), lambda x: x != "")
    items = runs(table(spark, sf_dir, "benchmark"), "item_id", True).select("item_id", "h", "run").distinct()
    items = F.broadcast(items) if items.count() <= 1_000_000 else items
    # documents send a hash and a place a run, however long they are; their words are looked at again where hashes met
    docs = spread(table(spark, sf_dir, "documents"))
    met = runs(docs, "doc_id", False).join(items, "h").select("doc_id", "i", "item_id", "run").distinct()
    found = docs.select("doc_id", words().alias("w")).join(met, "doc_id").where(run("w", F.col("i")) == F.col("run"))
    hits = found.select("item_id", "doc_id", "run").distinct()
    return hits.groupBy("item_id").agg(F.count_distinct("doc_id").alias("documents"), F.count_distinct("run").alias("shared"))


@query(f"""WITH {_DIGESTS}, s(style) AS (VALUES ('filter-first'), ('join-first'), ('aggregate-first')),
c AS (SELECT CASE traj_id % 3 WHEN 0 THEN 'filter-first' WHEN 1 THEN 'join-first' ELSE 'aggregate-first' END AS style, traj_id, avg(h_step) AS h, count(*) AS n FROM d GROUP BY ALL),
u AS (SELECT style, n, h FROM c UNION ALL SELECT 'mixed', n, h FROM c)
SELECT style, count(*) AS chains, round(avg(n), 6) + 0.0 AS mean_steps, round(avg(h), 6) + 0.0 AS mean_entropy FROM u GROUP BY style""")
def source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains by generator style, and all styles mixed."""
    c = digests(spark, sf_dir).groupBy("traj_id").agg(F.avg("h_step").alias("h"), F.count("*").alias("n"))
    style = F.element_at(F.array(F.lit("filter-first"), F.lit("join-first"), F.lit("aggregate-first")), (F.col("traj_id") % 3 + 1).cast("int"))
    both = c.select(F.explode(F.array(style, F.lit("mixed"))).alias("style"), "n", "h")
    return r6(both.groupBy("style").agg(F.count("*").alias("chains"), F.avg("n").alias("mean_steps"), F.avg("h").alias("mean_entropy")))

