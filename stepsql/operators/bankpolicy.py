"""Policies over the bank's menus: cold start, sampling, scores, selection and step-rewarded updates on executed chains.

A policy is a table: run, qid, slot, state, token, error_type, logit. `state` is 1 once a chain has left the gold texts, so what a policy does
next depends on the prefix. `run` names a policy; several are sampled and updated side by side. Chains are looked up among those that
bankrun has executed. Nothing here grows with the tables."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.ml.feature import HashingTF
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stepsql.config import RewardConfig, SftConfig, TrainConfig
from stepsql.sources.shared import written

from . import advantage as adv
from . import labels as mc
from .policy import uniform
from .reward import graded_outcome, step_reward
from .scorer import fit_scorer, score
from .select import best_of_n

CONTEXT = ("run", "qid", "slot", "state")
MENU = "qid bigint, slot int, token int, error_type string, sql string"


@dataclass(frozen=True)
class Habits:
    """How a generator of training chains slips: how often, how often after a slip, and how much more often by error type."""

    name: str = "mixed"
    slip: float = 0.2
    again: float = 0.45
    liking: dict[str, float] = field(default_factory=dict)


#: Generators with slips of their own kinds, and the mix of all.
SOURCES = (
    Habits("filter-first", liking={"filter condition": 4.0, "condition": 4.0, "format": 4.0}),
    Habits("join-first", liking={"join keys": 4.0, "table selection": 4.0, "null handling": 4.0}),
    Habits("aggregate-first", liking={"aggregation": 4.0, "math formula": 4.0, "complex operation": 4.0}),
)


def softmax(policy: DataFrame, by: tuple[str, ...] = CONTEXT) -> DataFrame:
    """Adds p and entropy."""
    own = Window.partitionBy(*by)
    e = policy.withColumn("e_", F.exp(F.col("logit") - F.max("logit").over(own)))
    p = e.withColumn("p", F.col("e_") / F.sum("e_").over(own)).drop("e_")
    return p.withColumn("entropy", -F.sum(F.col("p") * F.ln(F.greatest("p", F.lit(1e-12)))).over(own))


def generator(menu: DataFrame, habits: Habits) -> DataFrame:
    """The policy of a generator with these habits; the mass of a slip is dealt out by liking and by a hash of the option."""
    both = menu.withColumn("state", F.explode(F.array(F.lit(0), F.lit(1))))
    liking = _liking(habits)
    own = Window.partitionBy("qid", "slot", "state")
    mass = F.when(F.col("token") == 0, F.lit(0.0)).otherwise(liking * (0.5 + uniform("qid", "slot", "token", seed=11)))
    slips = F.sum(mass).over(own)
    slip = F.when(slips > 0, F.when(F.col("state") == 1, F.lit(habits.again)).otherwise(F.lit(habits.slip))).otherwise(F.lit(0.0))
    p = F.when(F.col("token") == 0, 1 - slip).otherwise(slip * mass / slips)
    return both.withColumn("logit", F.ln(p)).select(F.lit(habits.name).alias("run"), "qid", "slot", "state", "token", "error_type", "logit")


def _liking(habits: Habits) -> Column:
    out = F.lit(1.0)
    for kind, more in habits.liking.items():
        out = F.when(F.col("error_type") == kind, F.lit(more)).otherwise(out)
    return out


def sample(policy: DataFrame, n: int, salt: int, temperature: float = 1.0, greedy: bool = False, paired: bool = False) -> DataFrame:
    """run, qid, cand, step_no, token, state, p, h_step, chain: n chains a question, a row a step; chain is the options so far. One fold a chain over
    its question's options, so no loop over steps. Paired policies meet the same draws."""
    heat = softmax(policy if temperature == 1.0 else policy.withColumn("logit", F.col("logit") / temperature))
    spots = heat.groupBy(*CONTEXT).agg(F.array_sort(F.collect_list(F.struct("token", "p"))).alias("t"), F.max("entropy").alias("h"))
    grid = spots.groupBy("run", "qid").agg(F.max("slot").alias("slots"), F.map_from_entries(F.collect_list(F.struct((F.col("slot") * 2 + F.col("state")).alias("k"), F.struct("t", "h").alias("v")))).alias("grid"))
    asks = grid.withColumn("cand", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))

    def pick(slot: Column, spot: Column) -> Column:
        if greedy:
            return F.array_max(F.transform(spot["t"], lambda x: F.struct(x["p"].alias("p"), (-x["token"]).alias("o"), x.alias("x"))))["x"]
        u = uniform(*([] if paired else ["run"]), "qid", "cand", slot, F.lit(salt))
        found = F.aggregate(
            spot["t"], F.struct(F.lit(0.0).alias("sum"), F.lit(None).cast("struct<token:int,p:double>").alias("x")),
            lambda a, x: F.struct((a["sum"] + x["p"]).alias("sum"), F.when(a["x"].isNull() & (a["sum"] + x["p"] > u), x).otherwise(a["x"]).alias("x")),
            lambda a: a["x"],
        )
        return F.coalesce(found, F.element_at(spot["t"], -1))

    def step(held: Column, slot: Column) -> Column:
        state = F.when(F.exists(held, lambda x: x["token"] > 0), F.lit(1)).otherwise(F.lit(0))
        spot = F.element_at("grid", slot * 2 + state)
        x = pick(slot, spot)
        chain = F.concat(F.coalesce(F.concat(F.get(held, F.size(held) - 1)["chain"], F.lit("-")), F.lit("")), x["token"].cast("string"))
        return F.concat(held, F.array(F.struct(slot.alias("step_no"), x["token"].alias("token"), state.alias("state"), x["p"].alias("p"), spot["h"].alias("h_step"), chain.alias("chain"))))

    start = F.array().cast("array<struct<step_no:int,token:int,state:int,p:double,h_step:double,chain:string>>")
    return asks.select("run", "qid", "cand", F.inline(F.aggregate(F.sequence(F.lit(1), F.col("slots")), start, step)))


def cold_start(menu: DataFrame, corpus: DataFrame, run: str, prior: float = 4.0, alpha: float = 1.0, spread: float = 1.2) -> DataFrame:
    """The policy fitted to a corpus (qid, step_no, state, token) by counting. What it knew before stands in its prior: how often each error type was taken
    where it was offered, by state, and a leaning of its own towards each option (a hash, as wide as spread), which is all that questions without a corpus
    have; a question's own counts are added to it."""
    both = menu.withColumn("state", F.explode(F.array(F.lit(0), F.lit(1))))
    own = corpus.groupBy("qid", F.col("step_no").alias("slot"), "state", "token").agg(F.count("*").alias("n"))
    seen = corpus.groupBy("qid", F.col("step_no").alias("slot"), "state").agg(F.count("*").alias("all"))
    offered = both.join(seen, ["qid", "slot", "state"]).join(own, ["qid", "slot", "state", "token"], "left")
    rate = offered.groupBy("error_type", "state").agg(((F.sum(F.coalesce("n", F.lit(0))) + alpha) / (F.sum("all") + 4 * alpha)).alias("rate"))
    base = both.join(rate, ["error_type", "state"], "left").fillna(0.05, ["rate"])
    spot = Window.partitionBy("qid", "slot", "state")
    leaning = F.exp(spread * 3**0.5 * (uniform("qid", "slot", "token", seed=29) + uniform("qid", "slot", "token", seed=30) - 1) * 2**0.5)
    held = base.withColumn("mass", F.col("rate") * leaning).withColumn("p0", F.col("mass") / F.sum("mass").over(spot)).join(own, ["qid", "slot", "state", "token"], "left").join(seen, ["qid", "slot", "state"], "left").fillna(0, ["n", "all"])
    return held.select(F.lit(run).alias("run"), "qid", "slot", "state", "token", "error_type", F.ln((F.col("n") + prior * F.col("p0")) / (F.col("all") + prior)).alias("logit"))


def sft(policy: DataFrame, corpus: DataFrame, config: SftConfig = SftConfig(), rate: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """(policy, curve of epoch, mean_loss): the likelihood climbed by minibatches of chains, dealt out anew by a hash each epoch; a step of a batch adds the
    rate times mean(one-hot - p) to the logits. Counting reaches the same end at once; this is the form for models that have a gradient only."""
    spark = policy.sparkSession
    chains = corpus.select("qid", "cand").distinct().count()
    batches = max(1, -(-chains // config.batch))
    points = []
    tokens = corpus.select("qid", "cand", F.col("step_no").alias("slot"), "state", "token")
    for epoch in range(config.epochs):
        for b in range(batches):
            part = tokens.where(F.pmod(F.xxhash64("qid", "cand", F.lit(epoch)), F.lit(batches)) == b)
            hits = part.groupBy("qid", "slot", "state", "token").agg(F.count("*").alias("n"))
            all_ = hits.groupBy("qid", "slot", "state").agg(F.sum("n").alias("all"))
            up = softmax(policy).join(hits, ["qid", "slot", "state", "token"], "left").join(all_, ["qid", "slot", "state"], "left").fillna(0, ["n", "all"])
            policy = written(up.withColumn("logit", F.col("logit") + rate * (F.col("n") - F.col("all") * F.col("p"))).drop("p", "entropy", "n", "all").select(*CONTEXT, "token", "error_type", "logit"))
        loss = softmax(policy).join(tokens, ["qid", "slot", "state", "token"]).agg(F.avg(-F.ln("p")).alias("l")).first().l
        points.append((epoch + 1, loss))
    return policy, spark.createDataFrame(points, "epoch int, mean_loss double")


# --- scores ----------------------------------------------------------------------------------------

NUMBERS = ("ran", "failed", "log_rows", "growth", "same_rows", "empty", "repeats", "n_cols", "nulls", "joins", "aggregates", "filters", "words", "overlap", "is_last")


def features(runs: DataFrame, questions: DataFrame) -> DataFrame:
    """qid, split, chain, slot, prefix_key, whether it is a whole chain, and features of each distinct prefix: what its execution showed, the shape of
    its text, its overlap with the question's words, and hashed tokens."""
    one = runs.groupBy("qid", "chain").agg(*[F.first(c).alias(c) for c in ("split", "slot", "slots", "name", "sql", "prefix_key", "status", "n_rows", "n_cols", "nulls", "result_key")])
    parent = F.regexp_replace("chain", "-?[0-9]+$", "")
    before = one.select("qid", F.col("chain").alias("up"), F.col("n_rows").alias("rows_before"))
    earlier = one.select(F.col("qid").alias("q2"), F.col("chain").alias("c2"), F.col("result_key").alias("k2"))
    repeats = one.join(earlier, (F.col("qid") == F.col("q2")) & F.col("chain").startswith(F.concat(F.col("c2"), F.lit("-"))) & (F.col("result_key") == F.col("k2"))).select("qid", "chain").distinct().withColumn("repeats", F.lit(1.0))
    hits = lambda pattern: F.size(F.regexp_extract_all(F.lower("sql"), F.lit(pattern), F.lit(0))).cast("double")
    words = lambda c: F.filter(F.split(F.lower(c), "[^a-z0-9]+"), lambda w: w != "")
    rows = (
        one.withColumn("up", parent).join(before, ["qid", "up"], "left").join(repeats, ["qid", "chain"], "left").join(questions.select("qid", "question"), "qid")
        .select(
            "qid", "split", "chain", "slot", "slots", "name", "sql", "prefix_key", "result_key", "status",
            (F.col("status") == "ok").cast("double").alias("ran"), F.col("status").isin("invalid", "pruned", "runtime error").cast("double").alias("failed"),
            F.coalesce(F.log1p("n_rows"), F.lit(0.0)).alias("log_rows"), F.coalesce(F.log1p("n_rows") - F.log1p("rows_before"), F.lit(0.0)).alias("growth"),
            F.coalesce(F.col("n_rows") == F.col("rows_before"), F.lit(False)).cast("double").alias("same_rows"), F.coalesce(F.col("n_rows") == 0, F.lit(False)).cast("double").alias("empty"),
            F.coalesce("repeats", F.lit(0.0)).alias("repeats"), F.coalesce(F.col("n_cols").cast("double"), F.lit(0.0)).alias("n_cols"), F.coalesce("nulls", F.lit(0.0)).alias("nulls"),
            hits(r"\bjoin\b").alias("joins"), hits(r"\b(sum|avg|count|min|max)\(").alias("aggregates"), hits(r"\bwhere\b|\bhaving\b").alias("filters"), F.size(F.split("sql", " ")).cast("double").alias("words"),
            F.size(F.array_intersect(words("question"), words("sql"))).cast("double").alias("overlap"), (F.col("slot") == F.col("slots")).cast("double").alias("is_last"),
            F.split("sql", r"[^A-Za-z0-9_<>='%(*]+").alias("tokens"), words("question").alias("asked"),
        )
    )
    # words of the text, pairs of neighbours, and words met by words of the question
    pairs = F.zip_with("tokens", F.slice("tokens", 2, 10_000), lambda a, b: F.concat_ws(" ", a, b))
    crossed = F.flatten(F.transform("asked", lambda q: F.transform("tokens", lambda t: F.concat_ws("|", q, t))))
    return HashingTF(inputCol="text", outputCol="hashed", numFeatures=4096, binary=True).transform(rows.withColumn("text", F.concat("tokens", pairs, crossed)).drop("tokens", "asked"))


def prefix_labels(steps: DataFrame, runs: DataFrame) -> DataFrame:
    """qid, chain, sigma, visits: success rates of the prefixes of sampled, executed chains."""
    ends = runs.where("slot = slots").select("qid", F.col("chain").alias("whole"), "outcome")
    chains = steps.groupBy("run", "qid", "cand").agg(F.array_sort(F.collect_list(F.struct("step_no", "chain"))).alias("s")).select(
        "qid", F.concat_ws("|", "run", "cand").alias("traj_id"), F.transform("s", lambda x: x["chain"]).alias("steps"), F.element_at("s", -1)["chain"].alias("whole")
    )
    return mc.visits(chains.join(ends, ["qid", "whole"]).withColumn("path", F.col("steps")), "path").groupBy("qid", F.element_at("path", F.col("depth")).alias("chain")).agg(F.avg("outcome").alias("sigma"), F.count("*").alias("visits"))


def fit_scores(feats: DataFrame, labels: DataFrame, runs: DataFrame, kind: str = "logreg") -> DataFrame:
    """qid, chain, score, orm of every prefix: the step model is fitted to the success labels of prefixes of the training questions, the outcome model to the
    outcomes of whole chains alone; both then stay as they are."""
    names = [*NUMBERS, "hashed"]
    train = feats.where("split = 'train'").join(labels, ["qid", "chain"])
    ends = train.where("is_last = 1").join(runs.where("slot = slots").select("qid", "chain", F.col("outcome").cast("double").alias("y")), ["qid", "chain"])
    step, whole = fit_scorer(train, names, "sigma", kind), fit_scorer(ends, names, "y", kind)
    orm = score(whole, feats).select("qid", "chain", F.col("score").alias("orm"))
    return score(step, feats).select("qid", "chain", "score").join(orm, ["qid", "chain"])


def scored_steps(steps: DataFrame, scores: DataFrame, runs: DataFrame) -> DataFrame:
    """STEP rows of sampled chains: qid is run|question, so that several policies are groups of their own."""
    ends = runs.where("slot = slots").select("qid", F.col("chain").alias("whole"), "outcome", "status", "result_key", "split", "tier", "db", "first_error", "inferred")
    whole = steps.groupBy("run", "qid", "cand").agg(F.max_by("chain", "step_no").alias("whole"))
    found = steps.join(scores.select("qid", "chain", "score", "orm"), ["qid", "chain"]).join(whole, ["run", "qid", "cand"]).join(ends, ["qid", "whole"])
    return found.withColumn("question", F.col("qid")).withColumn("qid", F.concat_ws("|", "run", "question")).withColumn("traj_id", F.col("cand")).withColumn("n_tokens", F.lit(1))


def rewarded(steps: DataFrame, config: RewardConfig = RewardConfig(norm_scope="corpus")) -> DataFrame:
    return step_reward(steps, config)


def candidates(steps: DataFrame) -> DataFrame:
    """A row a sampled chain from rewarded steps: run, qid, question, cand, n_steps, reward, orm, outcome, result_key (null if it did not run), logp, and what is known of it."""
    return steps.groupBy("run", "qid", "question", "cand").agg(
        F.max("step_no").alias("n_steps"), F.max_by("reward", "step_no").alias("reward"), F.max_by("orm", "step_no").alias("orm"), F.max("outcome").alias("outcome"),
        F.max("result_key").alias("result_key"), F.sum(F.ln("p")).alias("logp"), F.avg("h_step").alias("entropy"),
        *[F.first(c).alias(c) for c in ("whole", "status", "split", "tier", "db", "first_error", "inferred")],
    )


# --- updates ---------------------------------------------------------------------------------------


@contextmanager
def brief(spark: SparkSession) -> Iterator[None]:
    """Settings for many short jobs over the bank's small tables, where planning anew by stages, compiling and starting tasks would take most of the time; what the session had is put back."""
    settings = {"spark.sql.adaptive.enabled": "false", "spark.sql.codegen.wholeStage": "false", "spark.sql.codegen.factoryMode": "NO_CODEGEN", "spark.sql.shuffle.partitions": "2"}
    before = {key: spark.conf.get(key, None) for key in settings}
    for key, value in settings.items():
        spark.conf.set(key, value)
    try:
        yield
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


def update(policy: DataFrame, scores: DataFrame, runs: DataFrame, config: TrainConfig, number: int) -> DataFrame:
    """The policies after one round. policy has a reference logit `ref` beside `logit`. Groups are sampled from the policy as it was; the clipped surrogate's gradient, with ratios to
    that policy (or to the reference), is climbed `inner` times, less the penalty for leaving the reference. A part of each option's step goes to all options of its error type
    and state, which is what carries over to other questions. Runs whose name begins with `outcome` or `graded` get no step rewards. What the sampled chains say of an option is summed
    once, by the sign of the advantage, as all of them share its ratio; the steps are then windows over the options."""
    own, kind = Window.partitionBy(*CONTEXT), Window.partitionBy("run", "error_type", "state")
    drawn = written(sample(policy.join(runs.where("split = 'train'").select("qid").distinct(), "qid"), config.group, number * 1000 + config.seed, config.temperature))
    found = written(scored_steps(drawn, scores, runs).select("run", "qid", "question", "traj_id", "step_no", "state", "token", "score", "h_step", "n_tokens", "outcome", "status"))
    plain = F.when(F.col("run").startswith("graded"), graded_outcome(F.col("outcome"), F.col("status") == "ok")).when(F.col("run").startswith("outcome"), F.col("outcome").cast("double"))
    steps = adv.raw(rewarded(found)).withColumn("adv_raw", F.coalesce(plain, "adv_raw")).withColumn("len", F.sum("n_tokens").over(Window.partitionBy("qid", "traj_id")))
    part, up = F.col("adv") / F.col("len") / config.group, F.col("adv") >= 0
    pulls = adv.standardise(steps).groupBy("run", F.col("question").alias("qid"), F.col("step_no").alias("slot"), "state", "token").agg(F.sum(F.when(up, part)).alias("up"), F.sum(F.when(~up, part)).alias("down"))
    places = policy.groupBy("run", "error_type", "state").agg(F.count_distinct("qid", "slot").alias("places"))
    old = softmax(policy).drop("entropy").withColumnsRenamed({"p": "p_old", "logit": "now", "ref": "logit"})
    both = softmax(old).drop("entropy").withColumnsRenamed({"p": "p_ref", "logit": "ref", "now": "logit"})
    policy = written(both.join(pulls, [*CONTEXT, "token"], "left").fillna(0.0, ["up", "down"]).join(places, ["run", "error_type", "state"]))
    rho, drift = F.col("p") / F.col("p_old" if config.ratio_base == "old" else "p_ref"), F.ln(F.col("p") / F.col("p_ref"))
    pull = rho * (F.when(rho < 1 + config.clip, F.col("up")).otherwise(F.lit(0.0)) + F.when(rho > 1 - config.clip, F.col("down")).otherwise(F.lit(0.0)))
    for _ in range(config.inner):
        now = softmax(policy).drop("entropy").withColumn("gain", pull)
        step = now.withColumn("g", F.col("gain") - F.col("p") * F.sum("gain").over(own) - config.kl * F.col("p") * (drift - F.sum(F.col("p") * drift).over(own)))
        policy = step.withColumn("logit", F.col("logit") + config.rate * (F.col("g") + config.sharing * F.sum("g").over(kind) / F.col("places"))).drop("p", "gain", "g")
    return written(policy.select(*CONTEXT, "token", "error_type", "ref", "logit"))


def dev_accuracy(policy: DataFrame, runs: DataFrame, n: int = 8) -> DataFrame:
    """run, split, protocol, accuracy: of the likeliest chains (`greedy`), and on average over n samples at temperature one, the same draws for every policy and round (`sampled`)."""
    ends = runs.where("slot = slots").select("qid", "chain", "split", "outcome")
    both = sample(policy, 1, 0, greedy=True).withColumn("protocol", F.lit("greedy")).unionByName(sample(policy, n, 777, paired=True).withColumn("protocol", F.lit("sampled")))
    whole = both.groupBy("run", "protocol", "qid", "cand").agg(F.max_by("chain", "step_no").alias("chain"))
    return whole.join(ends, ["qid", "chain"]).groupBy("run", "split", "protocol").agg((100 * F.avg("outcome")).alias("accuracy"))


def train(start: DataFrame, names: tuple[str, ...], scores: DataFrame, runs: DataFrame, config: TrainConfig = TrainConfig()) -> tuple[DataFrame, DataFrame]:
    """(policies, curve of method, seed, round, split, protocol, accuracy) from one cold-started policy: every name (method|seed) is a run of its own, side by side. The policies of
    all rounds are measured at the end, in one go."""
    spark = start.sparkSession
    runs_ = spark.createDataFrame([(n,) for n in names], "name string")
    ends, known = written(runs.where("slot = slots").coalesce(1)), written(scores.coalesce(1))  # a row a chain and a prefix of the menus, read every round
    with brief(spark):
        policy = written(start.crossJoin(F.broadcast(runs_)).select(F.col("name").alias("run"), "qid", "slot", "state", "token", "error_type", F.col("logit").alias("ref"), "logit"))  # a row a run
        rounds = [policy]
        for number in range(1, config.rounds + 1):
            policy = update(policy, known, ends, config, number)
            rounds.append(policy)
    every = rounds[0].withColumn("round", F.lit(0))
    for number, p in enumerate(rounds[1:], 1):
        every = every.unionByName(p.withColumn("round", F.lit(number)))
    curve = written(dev_accuracy(written(every.withColumn("run", F.concat_ws("|", "run", "round")).drop("round")), ends))
    parts = F.split("run", r"\|")
    return policy, curve.select(parts[0].alias("method"), parts[1].cast("int").alias("seed"), parts[2].cast("int").alias("round"), "split", "protocol", "accuracy")


def chosen(cands: DataFrame, n: int, by: str) -> DataFrame:
    """The outcome of the rule's choice among the first n candidates: by `reward`, `orm`, `vote` or `weighted` vote, `first`, or `any` (whether one of them is right)."""
    some = cands.where(F.col("cand") < n)
    fields = ("run", "qid", "question", "split", "tier", "db", "outcome", "first_error", "inferred", "whole")
    if by == "any":
        return some.groupBy("run", "qid", "question", "split", "tier", "db").agg(F.max("outcome").alias("outcome"), F.first("first_error").alias("first_error"), F.first("inferred").alias("inferred"), F.first("whole").alias("whole")).select(*fields)
    if by in ("vote", "weighted"):
        weight = F.sum("reward") if by == "weighted" else F.count("*").cast("double")
        votes = some.where("result_key is not null").groupBy("qid", "result_key").agg(weight.alias("votes"), F.min("cand").alias("cand"))
        top = votes.groupBy("qid").agg(F.max(F.struct("votes", (-F.col("cand")).alias("c"))).alias("t")).select("qid", (-F.col("t.c")).alias("cand"))
        # where nothing ran the first candidate stands
        picked = some.select("qid").distinct().join(top, "qid", "left").select("qid", F.coalesce("cand", F.lit(0)).alias("cand"))
        return some.join(picked, ["qid", "cand"]).select(*fields)
    if by == "first":
        return some.where("cand = 0").select(*fields)
    return best_of_n(some, n, by).select(*fields)


def menu_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, MENU)


# --- search and beam -------------------------------------------------------------------------------


def search_tree(policy: DataFrame, runs: DataFrame, iterations: int, rules: tuple[str, ...] = ("uct", "puct", "none"), c: float = 2**0.5, seed: int = 5) -> DataFrame:
    """rule, qid, depth, chain, visits, wins, sigma of searches over one policy's menus: every round each question walks down once a rule to a whole chain, whose outcome is added
    to all prefixes on the way. Rules: `uct` (mean success plus exploration, unvisited first), `puct` (exploration in proportion to the policy's probability), `none` (plain sampling)."""
    spark = policy.sparkSession
    options = written(softmax(policy).select("qid", "slot", "state", "token", "p"))
    ends = runs.where("slot = slots").select("qid", "chain", "outcome")
    slots = written(options.groupBy("qid").agg(F.max("slot").alias("slots")))
    deepest = slots.agg(F.max("slots").alias("m")).first().m
    nodes = written(spark.createDataFrame([], "rule string, qid bigint, depth int, chain string, visits bigint, wins bigint"))
    start = slots.select(F.explode(F.array(*map(F.lit, rules))).alias("rule"), "qid", "slots", F.lit("").alias("chain"), F.lit(0).alias("state"), F.array().cast("array<string>").alias("path"))
    for number in range(iterations):
        walk = start
        for slot in range(1, deepest + 1):
            going = walk.where(F.col("slots") >= slot).join(options.where(F.col("slot") == slot).drop("slot"), ["qid", "state"])
            here = going.withColumn("next", F.concat("chain", F.lit("-" if slot > 1 else ""), F.col("token").cast("string")))
            known = nodes.where(F.col("depth") == slot).select("rule", "qid", F.col("chain").alias("next"), "visits", "wins")
            seen = here.join(known, ["rule", "qid", "next"], "left").fillna(0, ["visits", "wins"])
            total = F.sum("visits").over(Window.partitionBy("rule", "qid"))
            mean = F.when(F.col("visits") > 0, F.col("wins") / F.col("visits")).otherwise(F.lit(0.0))
            draw = uniform("rule", "qid", "next", F.lit(number), seed=seed)
            uct = F.when(F.col("visits") == 0, F.lit(1e9)).otherwise(mean + c * F.sqrt(F.ln(total + 1) / F.greatest(F.col("visits"), F.lit(1))))
            puct = mean + c * F.col("p") * F.sqrt(total + 1) / (1 + F.col("visits"))
            plain = F.ln("p") - F.ln(-F.ln(F.greatest(draw, F.lit(1e-12))))  # the largest is a draw from p
            bound = F.when(F.col("rule") == "uct", uct).when(F.col("rule") == "puct", puct).otherwise(plain)
            best = seen.withColumn("b", F.struct(bound.alias("b"), draw.alias("u"))).groupBy("rule", "qid").agg(F.max(F.struct("b", "next", "slots", "state", "token", "path")).alias("x"))
            moved = best.select("rule", "qid", "x.slots", F.col("x.next").alias("chain"), F.when(F.col("x.token") > 0, F.lit(1)).otherwise(F.col("x.state")).alias("state"), F.concat("x.path", F.array("x.next")).alias("path"))
            walk = moved.unionByName(walk.where(F.col("slots") < slot))
        new = walk.join(ends, ["qid", "chain"]).select("rule", "qid", F.posexplode("path").alias("d", "chain"), "outcome")
        new = new.select("rule", "qid", (F.col("d") + 1).alias("depth"), "chain", F.lit(1).cast("bigint").alias("visits"), F.col("outcome").cast("bigint").alias("wins"))
        nodes = written(nodes.union(new).groupBy("rule", "qid", "depth", "chain").agg(F.sum("visits").alias("visits"), F.sum("wins").alias("wins")))
    return nodes.withColumn("sigma", F.col("wins") / F.col("visits"))


def beam(policy: DataFrame, scores: DataFrame, width: int = 2) -> DataFrame:
    """qid, rank, chain, reward: chains grown slot by slot, of which the `width` of largest step reward are kept a question. Weights fall with the running entropy
    over what the question's slots can add up to."""
    p = softmax(policy).select("qid", "slot", "state", "token", "entropy")
    top = p.groupBy("qid", "slot").agg(F.max("entropy").alias("h")).groupBy("qid").agg(F.sum("h").alias("h_max"), F.max("slot").alias("slots"))
    held = top.select("qid", "slots", "h_max", F.lit("").alias("chain"), F.lit(0).alias("state"), *[F.lit(0.0).alias(c) for c in ("h", "den", "num", "plain", "reward")])
    for slot in range(1, top.agg(F.max("slots").alias("m")).first().m + 1):
        going = held.where(F.col("slots") >= slot).join(p.where(F.col("slot") == slot).drop("slot"), ["qid", "state"])
        grown = going.withColumn("chain", F.concat("chain", F.lit("-" if slot > 1 else ""), F.col("token").cast("string"))).join(scores.select("qid", "chain", "score"), ["qid", "chain"])
        h = F.col("h") + F.col("entropy")
        w = F.when(F.col("h_max") > 0, 1 - h / F.col("h_max")).otherwise(F.lit(1.0))
        mass, weighted, plain = F.col("den") + w, F.col("num") + w * F.col("score"), F.col("plain") + F.col("score")
        step = F.when(mass > 1e-12, weighted / mass).otherwise(plain / slot)
        order = Window.partitionBy("qid").orderBy(F.desc("reward"), "chain")
        grown = grown.select(
            "qid", "slots", "h_max", "chain", F.when(F.col("token") > 0, F.lit(1)).otherwise(F.col("state")).alias("state"),
            h.alias("h"), mass.alias("den"), weighted.alias("num"), plain.alias("plain"), (F.col("reward") + step).alias("reward"),
        )
        kept = grown.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= width).drop("rank")
        held = kept.unionByName(held.where(F.col("slots") < slot))
    order = Window.partitionBy("qid").orderBy(F.desc("reward"), "chain")
    return held.withColumn("rank", F.row_number().over(order)).select("qid", "rank", "chain", "reward")
