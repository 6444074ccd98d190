"""Step entropies, certainty weights, step rewards, advantages, losses, selection over the order log."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.config import RewardConfig, SearchConfig
from stepsql.operators import advantage as adv
from stepsql.operators import reward as rw
from stepsql.operators import select as sel
from stepsql.operators.policy import uniform
from stepsql.sources.carriers import trail_events, trail_orders

from .carrier_sql import EVENTS, ORDERS, rewards
from .registry import query

BUDGETS = SearchConfig().budgets


def r6(df: DataFrame, digits: int = 6) -> DataFrame:
    """Doubles rounded to six digits (or another number), as the SQL does."""
    return df.select(*[(F.round(c, digits) + 0.0).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


#: Quotients of short decimals often end in a 5 just where rounding cuts; moved off that tie, the last bit of a
#: sum no longer decides.
OFF = 3.3e-10


def r8(df: DataFrame) -> DataFrame:
    return df.select(*[(F.round(F.col(c) + OFF, 8) + 0.0).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


STEP = ("qid", "traj_id", "step_no")
_KEYS = "qid, traj_id, step_no"


def _reward_query(name: str, columns: tuple[str, ...], trail=trail_orders, trail_sql: str = ORDERS, **knobs) -> None:
    config = RewardConfig(entropy_mode=knobs.get("mode", "cumulative"), norm_scope=knobs.get("scope", "trajectory"), agg=knobs.get("agg", "sum"), use_weight=knobs.get("weight", True))
    sql = f"WITH {rewards(trail_sql, **knobs)} SELECT {_KEYS}, {', '.join(f'round({c} + {OFF}, 8) + 0.0 AS {c}' for c in columns)} FROM rewarded"

    @query(sql, name)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return r8(rw.step_reward(trail(spark, sf_dir), config).select(*STEP, *columns))


_reward_query("step_reward", ("w", "prefix_score", "reward"))
_reward_query("step_reward_group", ("w", "prefix_score", "reward"), scope="group")
_reward_query("step_reward_corpus", ("w", "prefix_score", "reward"), scope="corpus")
_reward_query("step_reward_step_mode", ("w", "prefix_score", "reward"), mode="step", scope="corpus")
_reward_query("step_reward_events", ("w", "prefix_score", "reward"), trail_events, EVENTS)
_reward_query("prefix_entropy", ("h_prefix",))
_reward_query("prefix_entropy_step", ("h_prefix",), mode="step")
_reward_query("prefix_entropy_mean", ("h_prefix",), mode="mean_prefix")
_reward_query("certainty_weight", ("w",))
_reward_query("certainty_weight_group", ("w",), scope="group")
_reward_query("certainty_weight_corpus", ("w",), scope="corpus")
_reward_query("prefix_score", ("prefix_score",))
_reward_query("reward_no_weight", ("reward",), weight=False)
_reward_query("reward_mean", ("reward",), agg="mean")
_reward_query("reward_last", ("reward",), agg="last")


@query(f"WITH {rewards()}, l AS (SELECT qid, traj_id, max(step_no) AS n FROM trail GROUP BY ALL) SELECT r.qid, r.traj_id, round(reward + {OFF}, 8) + 0.0 AS reward FROM rewarded r JOIN l ON r.qid = l.qid AND r.traj_id = l.traj_id AND r.step_no = l.n")
def step_reward_nested(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nested form, on a log gathered to one row a trajectory."""
    return r8(rw.nest(trail_orders(spark, sf_dir)).select("qid", "traj_id", rw.nested_reward(F.col("steps")).alias("reward")))


@query(f"WITH {ORDERS}, cut AS (SELECT *, max(step_no) OVER (PARTITION BY qid, traj_id) AS last FROM trail) SELECT qid, traj_id, count(*) AS steps FROM cut WHERE step_no < last GROUP BY ALL")
def reward_without_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps that count when the closing query is left out."""
    got = rw.step_reward(trail_orders(spark, sf_dir), RewardConfig(include_final=False))
    return got.groupBy("qid", "traj_id").agg(F.count("reward").alias("steps"))


@query(f"WITH {EVENTS} SELECT step_no, outcome, count(*) AS steps, round(avg(h_step), 6) + 0.0 AS mean_entropy FROM trail GROUP BY ALL")
def entropy_trend(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean step entropy by step position, for trajectories that succeed and fail."""
    return r6(trail_events(spark, sf_dir).groupBy("step_no", "outcome").agg(F.count("*").alias("steps"), F.avg("h_step").alias("mean_entropy")))


@query(f"WITH {EVENTS}, s AS (SELECT outcome, traj_id, CASE WHEN count(*) > 1 THEN regr_slope(h_step, step_no) END AS slope FROM trail GROUP BY qid, traj_id, outcome) SELECT outcome, count(slope) AS chains, round(avg(slope), 6) + 0.0 AS mean_slope FROM s GROUP BY outcome")
def entropy_slope(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean slope of step entropy along a chain, by outcome."""
    per = trail_events(spark, sf_dir).groupBy("outcome", "qid", "traj_id").agg(F.regr_slope("h_step", "step_no").alias("slope"))
    return r6(per.groupBy("outcome").agg(F.count("slope").alias("chains"), F.avg("slope").alias("mean_slope")))


#: One chain of four steps as (step, score, weight): the first step's score and weight and the last one's weight are reported values, the others lie between.
WALK = ((1, 0.88, 0.78), (2, 0.84, 0.83), (3, 0.86, 0.88), (4, 0.9, 0.93))


@query(f"""WITH w(step_no, score, w) AS (VALUES {", ".join(f"({n}, {s}::DOUBLE, {w}::DOUBLE)" for n, s, w in WALK)}),
p AS (SELECT a.step_no, a.score, a.w, sum(b.score * b.w) / sum(b.w) AS prefix_score FROM w a JOIN w b ON b.step_no <= a.step_no GROUP BY ALL)
SELECT a.step_no, a.score, a.w, round(a.prefix_score, 6) + 0.0 AS prefix_score, round(sum(b.prefix_score), 6) + 0.0 AS reward FROM p a JOIN p b ON b.step_no <= a.step_no GROUP BY ALL""")
def reward_walkthrough(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Step rewards of one chain from given scores and weights, step by step."""
    steps = spark.createDataFrame([(1, 1, *row) for row in WALK], "qid int, traj_id int, step_no int, score double, w double")
    return r6(rw.accumulate(steps).select("step_no", "score", "w", "prefix_score", "reward"))


@query(f"WITH {ORDERS}, n AS (SELECT *, row_number() OVER (PARTITION BY qid, traj_id ORDER BY step_no) AS k FROM trail) SELECT qid, traj_id, step_no, 1.0::DOUBLE AS prefix_score, k::DOUBLE AS reward FROM n")
def reward_no_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation without scores: weights alone leave every prefix at one, so a reward counts steps."""
    got = rw.step_reward(trail_orders(spark, sf_dir), RewardConfig(use_score=False))
    return r6(got.select("qid", "traj_id", "step_no", "prefix_score", "reward"))


# --- advantages -------------------------------------------------------------------------------

_RAW = f"""{rewards(scope="corpus")},
raws AS (
  SELECT *, outcome + sum(prefix_score) OVER (PARTITION BY qid, traj_id ORDER BY step_no ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS adv_raw
  FROM rewarded)"""
_CORPUS = RewardConfig(norm_scope="corpus")


def _raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    return adv.raw(rw.step_reward(trail_orders(spark, sf_dir), _CORPUS))


@query(f"WITH {_RAW} SELECT {_KEYS}, round(adv_raw + {OFF}, 8) + 0.0 AS adv_raw FROM raws")
def advantage_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r8(_raw(spark, sf_dir).select(*STEP, "adv_raw"))


def _standard(name: str, std: str, unit: str) -> None:
    n = "n_tokens" if unit == "token" else "1"
    dof = "- 1" if std == "sample" else ""
    sql = f"""WITH {_RAW},
moments AS (SELECT qid, sum({n}) AS n, sum({n} * adv_raw) / sum({n}) AS mean, min(adv_raw) AS lo, max(adv_raw) AS hi FROM raws GROUP BY qid),
squares AS (SELECT qid, sum({n} * (adv_raw - mean) ** 2) AS q FROM raws JOIN moments USING (qid) GROUP BY qid)
SELECT {_KEYS}, round(CASE WHEN lo = hi OR n {dof} <= 0 THEN 0.0 ELSE (adv_raw - mean) / sqrt(q / (n {dof})) END, 5) + 0.0 AS adv
FROM raws JOIN moments USING (qid) JOIN squares USING (qid)"""

    @query(sql, name)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return adv.standardise(_raw(spark, sf_dir), std, unit).select(*STEP, (F.round("adv", 5) + 0.0).alias("adv"))


_standard("advantage", "pop", "step")
_standard("advantage_sample", "sample", "step")
_standard("advantage_token", "pop", "token")


@query(f"WITH {_RAW} SELECT CASE WHEN n <= 2 THEN 'short' WHEN n <= 5 THEN 'medium' ELSE 'long' END AS length, round(var_pop(outcome), 6) + 0.0 AS outcome_only, round(var_pop(adv_raw), 6) + 0.0 AS with_steps FROM (SELECT *, max(step_no) OVER (PARTITION BY qid, traj_id) AS n FROM raws) GROUP BY ALL")
def signal_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variance of the signal with and without step rewards, by chain length."""
    from pyspark.sql import Window

    n = F.max("step_no").over(Window.partitionBy("qid", "traj_id"))
    rows = _raw(spark, sf_dir).withColumn("length", F.when(n <= 2, "short").when(n <= 5, "medium").otherwise("long"))
    return r6(rows.groupBy("length").agg(F.var_pop("outcome").alias("outcome_only"), F.var_pop("adv_raw").alias("with_steps")))


@query(f"WITH {_RAW}, c AS (SELECT qid, traj_id, max(outcome) AS o, max(prefix_score) AS p FROM raws GROUP BY ALL) SELECT count(*) AS chains, count(*) FILTER (o = 0) AS zero_outcome, count(*) FILTER (p = 0) AS zero_reward FROM c")
def signal_sparsity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains whose outcome is zero against chains whose every step reward is zero."""
    c = _raw(spark, sf_dir).groupBy("qid", "traj_id").agg(F.max("outcome").alias("o"), F.max("prefix_score").alias("p"))
    return c.agg(F.count("*").alias("chains"), F.count_if(F.col("o") == 0).alias("zero_outcome"), F.count_if(F.col("p") == 0).alias("zero_reward"))


# --- candidates: orders of a customer, by date of sampling (order key) -----------------------------

_CANDS = f"""{rewards(scope="corpus")},
chains AS (
  SELECT qid, traj_id, max(step_no)::INTEGER AS n_steps, round(max_by(reward, step_no), 9) AS reward, max(outcome) AS outcome,
    round(max_by(score, step_no), 9) AS orm, CASE WHEN max(step_no) > 1 THEN (traj_id % 3)::VARCHAR END AS result_key
  FROM rewarded GROUP BY qid, traj_id),
cands AS (SELECT *, (row_number() OVER (PARTITION BY qid ORDER BY traj_id) - 1)::INTEGER AS cand FROM chains)"""


def candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as candidates of their customer: reward as computed, orm the last step's score, result a class of three (none
    for one-step chains)."""
    from pyspark.sql import Window

    rows = rw.step_reward(trail_orders(spark, sf_dir), _CORPUS).groupBy("qid", "traj_id").agg(
        F.max("step_no").cast("int").alias("n_steps"), F.round(F.max_by("reward", "step_no"), 9).alias("reward"), F.max("outcome").alias("outcome"),
        F.round(F.max_by("score", "step_no"), 9).alias("orm"),
    )
    rows = rows.withColumn("result_key", F.when(F.col("n_steps") > 1, (F.col("traj_id") % 3).cast("string")))
    return rows.withColumn("cand", (F.row_number().over(Window.partitionBy("qid").orderBy("traj_id")) - 1).cast("int"))


def _best(name: str, by: str, n: int) -> None:
    sql = f"WITH {_CANDS} SELECT qid, cand, traj_id, outcome FROM cands WHERE cand < {n} QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {by} DESC, cand) = 1"

    @query(sql, name)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return sel.best_of_n(candidates(spark, sf_dir), n, by).select("qid", "cand", "traj_id", "outcome")


_best("best_of_n", "reward", 8)
_best("orm_select", "orm", 8)
_best("greedy_first", "reward", 1)


@query(f"WITH {_CANDS}, b(n) AS (VALUES {', '.join(f'({n})' for n in BUDGETS)}) SELECT qid, n::INTEGER AS n, cand, outcome FROM cands JOIN b ON cand < n QUALIFY row_number() OVER (PARTITION BY qid, n ORDER BY reward DESC, cand) = 1")
def best_of_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sel.best_curve(candidates(spark, sf_dir), BUDGETS)


def _vote(name: str, votes: str, weight: str | None) -> None:
    sql = f"""WITH {_CANDS}, v AS (SELECT qid, result_key, min(cand) AS cand, {votes} AS votes FROM cands WHERE result_key IS NOT NULL GROUP BY ALL)
SELECT qid, result_key, cand, votes FROM v QUALIFY row_number() OVER (PARTITION BY qid ORDER BY votes DESC, cand) = 1"""

    @query(sql, name)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        c = candidates(spark, sf_dir)
        return sel.majority_vote(c.withColumn("reward", F.round(F.col("reward") * 1e6).cast("bigint")) if weight else c, None, weight)


_vote("self_consistency", "count(*)", None)
_vote("weighted_vote", "sum(round(reward * 1e6)::BIGINT)::BIGINT", "reward")


@query(f"WITH {_CANDS}, b(n) AS (VALUES {', '.join(f'({n})' for n in BUDGETS)}) SELECT qid, n::INTEGER AS n, max(outcome) AS passed FROM cands JOIN b ON cand < n GROUP BY ALL")
def pass_at_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sel.pass_at_n(candidates(spark, sf_dir), BUDGETS)


@query(f"""WITH {_CANDS}, c AS (SELECT qid, count(*) AS t, sum(outcome) AS r FROM cands GROUP BY qid)
SELECT qid, round(CASE WHEN t - r < 4 THEN 1.0 ELSE 1 - (t-r)/t * ((t-r-1)/(t-1)) * ((t-r-2)/(t-2)) * ((t-r-3)/(t-3)) END, 6) + 0.0 AS estimate FROM c WHERE t >= 4""")
def pass_at_n_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return r6(sel.pass_at_n_estimate(candidates(spark, sf_dir), 4))


@query(f"WITH {_CANDS} SELECT a.qid, a.cand, count(b.cand) AS wins FROM cands a LEFT JOIN cands b ON a.qid = b.qid AND a.reward > b.reward GROUP BY ALL")
def pairwise_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairwise tournament: how many of its question's candidates each one beats."""
    return sel.pairwise_wins(candidates(spark, sf_dir)).withColumn("wins", F.col("wins").cast("bigint"))


@query(f"""WITH {_CANDS}, g AS (SELECT qid, CASE WHEN outcome = 1 THEN 1.0 WHEN result_key IS NOT NULL THEN 0.1 ELSE 0.0 END::DOUBLE AS grade FROM cands)
SELECT qid, count(*) AS candidates, round(sum(grade), 6) + 0.0 AS total_grade, count(DISTINCT grade) AS grades FROM g GROUP BY qid""")
def graded_outcome(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcomes with partial credit for queries that run, a question at a time."""
    graded = candidates(spark, sf_dir).withColumn("grade", rw.graded_outcome(F.col("outcome"), F.col("result_key").isNotNull()))
    return r6(graded.groupBy("qid").agg(F.count("*").alias("candidates"), F.sum("grade").alias("total_grade"), F.count_distinct("grade").alias("grades")))


def _accuracy_sql(rule: str) -> str:
    return f"WITH {_CANDS}, b(n) AS (VALUES {', '.join(f'({n})' for n in BUDGETS)}), {rule}"


_METHODS = f"""{_accuracy_sql('''won AS (SELECT qid, n, outcome FROM cands JOIN b ON cand < n QUALIFY row_number() OVER (PARTITION BY qid, n ORDER BY reward DESC, cand) = 1),
orm AS (SELECT qid, n, outcome FROM cands JOIN b ON cand < n QUALIFY row_number() OVER (PARTITION BY qid, n ORDER BY orm DESC, cand) = 1),
votes AS (SELECT qid, n, result_key, min(cand) AS cand, count(*) AS k FROM cands JOIN b ON cand < n WHERE result_key IS NOT NULL GROUP BY ALL),
major AS (SELECT v.qid, n, outcome FROM (SELECT * FROM votes QUALIFY row_number() OVER (PARTITION BY qid, n ORDER BY k DESC, cand) = 1) v JOIN cands c ON c.qid = v.qid AND c.cand = v.cand),
passed AS (SELECT qid, n, max(outcome) AS outcome FROM cands JOIN b ON cand < n GROUP BY ALL),
every AS (SELECT 'step reward' AS method, * FROM won UNION ALL SELECT 'outcome model', * FROM orm UNION ALL SELECT 'self-consistency', * FROM major UNION ALL SELECT 'pass@n', * FROM passed)''')}
"""


def by_method(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, n, qid, outcome for every selection rule and budget; the candidates are computed once."""
    from stepsql.sources.shared import written

    c = written(candidates(spark, sf_dir))
    own = c.select("qid", "cand", "outcome")
    parts = [
        sel.best_curve(c, BUDGETS).select(F.lit("step reward").alias("method"), "n", "qid", "outcome"),
        sel.best_curve(c, BUDGETS, "orm").select(F.lit("outcome model").alias("method"), "n", "qid", "outcome"),
        sel.pass_at_n(c, BUDGETS).select(F.lit("pass@n").alias("method"), "n", "qid", F.col("passed").alias("outcome")),
    ]
    votes = c.where("result_key is not null").select("qid", "result_key", "cand", F.explode(F.filter(F.array(*map(F.lit, BUDGETS)), lambda n: n > F.col("cand"))).alias("n"))
    k = votes.groupBy("qid", "n", "result_key").agg(F.count("*").alias("k"), F.min("cand").alias("cand"))
    top = k.groupBy("qid", "n").agg(F.max(F.struct("k", (-F.col("cand")).alias("c"))).alias("t")).select("qid", "n", (-F.col("t.c")).alias("cand"))
    parts.append(top.join(own, ["qid", "cand"]).select(F.lit("self-consistency").alias("method"), "n", "qid", "outcome"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query(_METHODS + "SELECT method, n::INTEGER AS n, count(*) AS questions, round(100 * avg(outcome), 6) + 0.0 AS accuracy FROM every GROUP BY ALL")
def ex_by_method(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stepsql.operators.measures import accuracy

    return r6(accuracy(by_method(spark, sf_dir), "method", "n"))


@query(_METHODS + "SELECT count(*) AS questions, round(100 * avg(outcome), 6) + 0.0 AS accuracy FROM every WHERE method = 'step reward' AND n = 8")
def ex_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stepsql.operators.measures import accuracy

    return r6(accuracy(sel.best_curve(candidates(spark, sf_dir), (8,))))


@query(_METHODS + ", a AS (SELECT method, n, 100 * avg(outcome) AS x FROM every GROUP BY ALL) SELECT s.n::INTEGER AS n, round(s.x - g.x, 6) + 0.0 AS gain, round(p.x - s.x, 6) + 0.0 AS gap FROM a s JOIN a p ON p.n = s.n AND p.method = 'pass@n' JOIN a g ON g.n = 1 AND g.method = 'step reward' WHERE s.method = 'step reward'")
def sampling_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What sampling adds to the first candidate, and what a perfect choice would add to that."""
    from stepsql.operators.measures import accuracy

    a = accuracy(by_method(spark, sf_dir), "method", "n")
    t = a.groupBy("n").agg(F.max(F.when(F.col("method") == "step reward", F.col("accuracy"))).alias("s"), F.max(F.when(F.col("method") == "pass@n", F.col("accuracy"))).alias("p"))
    first = a.where("method = 'step reward' and n = 1").select(F.col("accuracy").alias("g"))
    return r6(t.crossJoin(F.broadcast(first)).select("n", (F.col("s") - F.col("g")).alias("gain"), (F.col("p") - F.col("s")).alias("gap")))  # one row


@query(_METHODS + ", a AS (SELECT n, 100 * avg(outcome) AS x FROM every WHERE method = 'step reward' GROUP BY n) SELECT round(regr_slope(x, ln(n)), 5) + 0.0 AS slope, round(regr_intercept(x, ln(n)), 5) + 0.0 AS intercept, round(regr_r2(x, ln(n)), 5) + 0.0 AS r2 FROM a")
def scaling_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stepsql.operators.measures import accuracy
    from stepsql.operators.measures import scaling_fit as fit

    got = fit(accuracy(sel.best_curve(candidates(spark, sf_dir), BUDGETS), "n"))
    return got.select(*[(F.round(c, 5) + 0.0).alias(c) for c in got.columns])


@query(_METHODS + ", a AS (SELECT method, n, 100 * avg(outcome) AS x FROM every WHERE method <> 'pass@n' GROUP BY ALL) SELECT method, n::INTEGER AS n, round(x, 6) + 0.0 AS accuracy FROM (SELECT *, max(x) OVER (ORDER BY n, x DESC, method ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM a) WHERE seen IS NULL OR x > seen")
def pareto_front(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Selection rules and budgets that no cheaper one matches."""
    from stepsql.operators.measures import accuracy

    return r6(sel.pareto(accuracy(by_method(spark, sf_dir).where("method <> 'pass@n'"), "method", "n").select("method", "n", "accuracy"), "n", "accuracy"))


@query()
def sample_uniforms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hash-seeded uniforms: one per question, sample and position."""
    rows = trail_orders(spark, sf_dir).select("qid", "traj_id", "step_no")
    return rows.withColumn("u", uniform("qid", "traj_id", "step_no"))
