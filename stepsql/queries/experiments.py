"""The experiments, run on the question bank: chains of the bank's menus are executed, sampled, scored, selected and learnt from.

No SQL: outcomes come from executing generated texts and from policies. What is executed and sampled is written once a session and folder, and every
table here is read from that. Figures are those of stand-in policies on 36 questions, not of language models."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stepsql.config import RewardConfig, SearchConfig, SftConfig, TrainConfig
from stepsql.operators import bankpolicy as bp
from stepsql.operators import bankrun
from stepsql.operators import chains as ch
from stepsql.operators import measures as ms
from stepsql.operators import select as sel
from stepsql.operators.chains import compose, flatten
from stepsql.operators.execute import REASONS, run_text
from stepsql.sources import bank
from stepsql.sources.shared import written

from .registry import query

BUDGETS = SearchConfig().budgets
RULES = (("step reward", "reward"), ("outcome model", "orm"), ("self-consistency", "vote"), ("weighted vote", "weighted"), ("pass@n", "any"))
RUNS_OF = tuple(f"{method}|{seed}" for method in ("step reward", "outcome only", "graded outcome") for seed in (17, 18, 19))


# --- what the experiments share ------------------------------------------------------------------------


def runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    def make() -> DataFrame:
        bank.prepare(spark, sf_dir)
        return bankrun.run_menus(spark, bank.QUESTIONS)

    return bankrun.kept(spark, sf_dir, "runs", make)


def menu(spark: SparkSession) -> DataFrame:
    return bp.menu_frame(spark, bankrun.menu_rows(bank.QUESTIONS))


def questions(spark: SparkSession, style: str = "plain") -> DataFrame:
    rows = [(q.qid, q.db, q.split, q.tier, q.question if style == "plain" else bank.wording(q.question, style, q.qid)) for q in bank.QUESTIONS]
    return spark.createDataFrame(rows, "qid bigint, db string, split string, tier string, question string")


def accepted(steps: DataFrame, done: DataFrame) -> DataFrame:
    """Steps of the sampled chains that hold no malformed block, undefined reference or name conflict."""
    bad = done.where(F.col("condition").isin(*REASONS)).select("qid", "chain").distinct()
    return steps.join(steps.join(bad, ["qid", "chain"]).select("run", "qid", "cand").distinct(), ["run", "qid", "cand"], "left_anti")


def generated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three chains a training question of each generator, and of the mix, at temperature one."""

    def make() -> DataFrame:
        train = questions(spark).where("split = 'train'").select("qid")
        own = menu(spark).join(train, "qid")
        policies = bp.generator(own, bp.Habits())
        for habits in bp.SOURCES:
            policies = policies.unionByName(bp.generator(own, habits))
        return bp.sample(policies, SearchConfig().samples_per_question, 41)

    return bankrun.kept(spark, sf_dir, "generated", make)


def policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The policy after its cold start on the mixed corpus."""
    corpus = accepted(generated(spark, sf_dir), runs(spark, sf_dir)).where("run = 'mixed'")
    return bankrun.kept(spark, sf_dir, "policy", lambda: bp.cold_start(menu(spark), corpus, "cold start"))


def rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bankrun.kept(spark, sf_dir, "rollouts", lambda: bp.sample(policy(spark, sf_dir), SearchConfig().label_rollouts, 5))


def scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """qid, chain, score, orm, sigma, visits and the split of every prefix."""

    def make() -> DataFrame:
        done = runs(spark, sf_dir)
        feats, labels = bp.features(done, questions(spark)), bp.prefix_labels(rollouts(spark, sf_dir), done)
        return bp.fit_scores(feats, labels, done).join(feats.select("qid", "chain", "split", "is_last"), ["qid", "chain"]).join(labels, ["qid", "chain"], "left")

    return bankrun.kept(spark, sf_dir, "scores", make)


def steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rewarded steps of 32 chains a question, sampled from the cold-started policy."""

    def make() -> DataFrame:
        drawn = bp.sample(policy(spark, sf_dir), max(BUDGETS), 99)
        return bp.rewarded(bp.scored_steps(drawn, scores(spark, sf_dir), runs(spark, sf_dir)))

    return bankrun.kept(spark, sf_dir, "steps", make)


def sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bankrun.kept(spark, sf_dir, "sampled", lambda: bp.candidates(steps(spark, sf_dir)))


def trained(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(policies, curve) of the step-rewarded runs, the outcome-only ones and those with partial credit, three seeds each."""
    done = {}

    def make(part: int):
        def run() -> DataFrame:
            if not done:
                done[0], done[1] = bp.train(policy(spark, sf_dir), RUNS_OF, scores(spark, sf_dir), runs(spark, sf_dir), TrainConfig())
            return done[part]

        return run

    first = bankrun.kept(spark, sf_dir, "trained", make(0))
    return first, bankrun.kept(spark, sf_dir, "curve", make(1))


def greedy(spark: SparkSession, of: DataFrame, done: DataFrame) -> DataFrame:
    """The likeliest chain of every question and policy, with its outcome."""
    best = bp.sample(of, 1, 0, greedy=True).groupBy("run", "qid").agg(F.max_by("chain", "step_no").alias("chain"))
    return best.join(done.where("slot = slots").select("qid", "chain", "split", "tier", "db", "outcome", "first_error", "inferred"), ["qid", "chain"])


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _with_all(df: DataFrame, column: str) -> DataFrame:
    """df, and once more with '(all)' in a column."""
    return df.unionByName(df.withColumn(column, F.lit("(all)")))


# --- candidates, corpus, labels, score model ----------------------------------------------------------------


@query()
def candidate_outcomes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every chain of the menus of all questions, run and compared with gold."""
    return runs(spark, sf_dir).where("slot = slots").select("qid", "chain", F.col("first_error").alias("error_type"), "slips", "inferred", "status", "outcome", "result_key", F.col("slots").alias("n_steps"), "seconds")


@query()
def error_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Injected against inferred error types over all chains with one slip that went wrong."""
    return runs(spark, sf_dir).where("slot = slots and slips = 1 and outcome = 0").groupBy(F.col("first_error").alias("error_type"), "inferred").agg(F.count("*").alias("n"))


@query()
def bank_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Corpus building by source: chains generated and accepted by the validator, steps a chain, words a step."""
    made, done = generated(spark, sf_dir), runs(spark, sf_dir)
    texts = done.groupBy("qid", "chain").agg(F.first(F.size(F.split("sql", r"\s+"))).alias("w"))
    size = lambda df: df.join(texts, ["qid", "chain"]).groupBy("run", "qid", "cand").agg(F.max("step_no").alias("k"), F.avg("w").alias("w"))
    all_, good = size(made), size(accepted(made, done))
    total = all_.groupBy("run").agg(F.count("*").alias("generated"))
    return good.groupBy("run").agg(F.count("*").alias("accepted"), F.avg("k").alias("mean_steps"), F.max("k").alias("max_steps"), F.avg("w").alias("step_words")).join(total, "run").select(
        F.col("run").alias("source"), "generated", "accepted", (100 * F.col("accepted") / F.col("generated")).alias("acceptance"), "mean_steps", "max_steps", "step_words"
    )


@query()
def sft_epochs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss by epoch of the minibatch form of the cold start, from a policy that knows nothing."""
    corpus = accepted(generated(spark, sf_dir), runs(spark, sf_dir)).where("run = 'mixed'")
    blank = policy(spark, sf_dir).withColumn("logit", F.lit(0.0)).join(corpus.select("qid").distinct(), "qid").select(*bp.CONTEXT, "token", "error_type", "logit")
    return bp.sft(blank, corpus, SftConfig())[1]


@query()
def bank_sigma(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Success labels of the prefixes of executed rollouts, by depth: nodes, visits, nodes that are neither all right nor all wrong, mean label."""
    done = runs(spark, sf_dir)
    labels = bp.prefix_labels(rollouts(spark, sf_dir), done).join(done.groupBy("qid", "chain").agg(F.first("slot").alias("depth"), F.first("split").alias("split")), ["qid", "chain"])
    return labels.groupBy("split", "depth").agg(F.count("*").alias("nodes"), F.sum("visits").alias("visits"), F.count_if((F.col("sigma") > 0) & (F.col("sigma") < 1)).alias("mixed"), F.avg("sigma").alias("mean_sigma"))


@query()
def scorer_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of every executed prefix by the step model (fitted to success labels) and by the outcome model, with the label where there is one."""
    return scores(spark, sf_dir).select("qid", "chain", "split", "score", "orm", "sigma", "visits")


@query()
def bank_input(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a score model would read of every chain of the menus: the question, and each fragment with what it gave when run, a checkpoint mark after each."""
    result = F.when(F.col("status") == "ok", F.concat(F.col("n_rows").cast("string"), F.lit(" rows, "), F.col("n_cols").cast("string"), F.lit(" columns"))).otherwise(F.concat_ws(": ", "status", "condition"))
    part = F.concat(F.col("name"), F.lit(": "), F.col("sql"), F.lit(" -> "), result, F.lit(" <step>"))
    chains = runs(spark, sf_dir).groupBy("qid", "whole").agg(F.array_sort(F.collect_list(F.struct("slot", part.alias("t")))).alias("parts"), F.max("outcome").alias("outcome"))
    return chains.join(questions(spark).select("qid", "question"), "qid").select("qid", F.col("whole").alias("chain"), F.concat_ws("\n", "question", F.concat_ws("\n", F.transform("parts", lambda x: x["t"]))).alias("input"), "outcome")


@query()
def bank_diversity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct chains among the sampled completions of each question, and the share of duplicates."""
    whole = rollouts(spark, sf_dir).groupBy("qid", "cand").agg(F.max_by("chain", "step_no").alias("chain"))
    return whole.groupBy("qid").agg(F.count("*").alias("completions"), F.count_distinct("chain").alias("paths")).withColumn("duplicate_share", 1 - F.col("paths") / F.col("completions"))


@query()
def scorer_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cross-entropy and area under the curve of step scores against the outcomes of sampled chains, for training and held-out questions."""
    s = steps(spark, sf_dir).select("split", "score", "outcome")
    loss = _union([ms.bce(s.where(F.col("split") == x), "outcome").withColumn("split", F.lit(x)) for x in ("train", "held out")])
    by = s.groupBy("split", F.round("score", 6).alias("s")).agg(F.count_if(F.col("outcome") == 1).alias("p"), F.count_if(F.col("outcome") == 0).alias("n"))
    below = F.coalesce(F.sum("n").over(Window.partitionBy("split").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    auc = by.withColumn("below", below).groupBy("split").agg((F.sum(F.col("p") * (F.col("below") + F.col("n") / 2)) / (F.sum("p") * F.sum("n"))).alias("auc"))
    return loss.select("split", "rows", "mean_loss").join(auc, "split")


@query()
def bank_entropy_trend(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean step entropy and weight by place, for sampled chains that end right and wrong."""
    return steps(spark, sf_dir).groupBy("step_no", "outcome").agg(F.count("*").alias("steps"), F.avg("h_step").alias("entropy"), F.avg("w").alias("weight"), F.avg("score").alias("score"))


# --- main comparison, scaling, formats ------------------------------------------------------------------


def _methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, n, split, tier, db, question, outcome of every protocol."""
    c, done = sampled(spark, sf_dir), runs(spark, sf_dir)
    parts = [bp.chosen(c, n, by).select(F.lit(name).alias("method"), F.lit(n).alias("n"), "split", "tier", "db", "question", "outcome") for name, by in RULES for n in BUDGETS]
    parts.append(greedy(spark, policy(spark, sf_dir), done).select(F.lit("greedy").alias("method"), F.lit(1).alias("n"), "split", "tier", "db", F.col("qid").alias("question"), "outcome"))
    return _union(parts)


@query()
def bank_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Execution accuracy on the bank by decoding protocol, budget and split."""
    return ms.accuracy(_with_all(_methods(spark, sf_dir), "split"), "method", "n", "split")


@query()
def rl_selection(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy, gain for a doubling of candidates, and the gap to pass@n, of each rule and budget."""
    a = ms.accuracy(_methods(spark, sf_dir).where("method <> 'greedy'"), "method", "n")
    bound = a.where("method = 'pass@n'").select("n", F.col("accuracy").alias("bound"))
    return a.join(bound, "n").select("method", "n", "accuracy", (F.col("accuracy") - F.lag("accuracy").over(Window.partitionBy("method").orderBy("n"))).alias("gain"), (F.col("bound") - F.col("accuracy")).alias("gap"))


@query()
def bank_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slope and fit of accuracy on the logarithm of the candidates, by rule."""
    a = ms.accuracy(_methods(spark, sf_dir).where("method <> 'greedy'"), "method", "n")
    return _union([ms.scaling_fit(a.where(F.col("method") == name)).select(F.lit(name).alias("method"), "slope", "intercept", "r2") for name, _ in RULES])


@query()
def bank_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What eight candidates add to greedy decoding, by database and tier."""
    m = _methods(spark, sf_dir).where("method = 'greedy' or (method = 'step reward' and n = 8)")
    t = m.groupBy("db", "tier").agg(*[(100 * F.avg(F.when(F.col("method") == k, F.col("outcome")))).alias(a) for k, a in (("greedy", "greedy"), ("step reward", "selected"))])
    return t.withColumn("gain", F.col("selected") - F.col("greedy"))


def formats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """format, run, qid, split, cand, whole, outcome of eight sampled answers: step chains; rationales without steps (the same choices, but with nothing run on the way that tells
    whether the path was left, so as on average over both states as often as they occur); and direct queries (both states alike). All are executed, the last two as one flat query."""

    def make() -> DataFrame:
        bank.prepare(spark, sf_dir)
        done = runs(spark, sf_dir)
        flat = bankrun.run_flat(spark, bank.QUESTIONS, gold_keys={r.qid: r.gold_key for r in done.select("qid", "gold_key").distinct().collect()})
        own = policy(spark, sf_dir)
        shape = done.where("slot = slots").select("qid", "split", F.col("chain").alias("whole"), "outcome", "slips")
        # a flat query of two slips or more is as right as its chain, which was run
        truth = shape.join(flat.select("qid", "whole", "flat_outcome"), ["qid", "whole"], "left").withColumn("flat", F.coalesce("flat_outcome", "outcome"))
        left = rollouts(spark, sf_dir).agg(F.avg("state").alias("s")).first().s

        def mixed(share: float) -> DataFrame:
            p = F.sum(F.when(F.col("state") == 1, share * F.col("p")).otherwise((1 - share) * F.col("p")))
            flat_ = bp.softmax(own).groupBy("run", "qid", "slot", "token", "error_type").agg(F.ln(p).alias("logit"))
            return flat_.withColumn("state", F.explode(F.array(F.lit(0), F.lit(1))))

        blind, loose = mixed(left), mixed(0.5)
        parts = []
        for name, p, column in (("chain", own, "outcome"), ("rationale only", blind, "flat"), ("direct", loose, "flat")):
            whole = bp.sample(p.select(*bp.CONTEXT, "token", "error_type", "logit"), SearchConfig().candidates, 7).groupBy("run", "qid", "cand").agg(F.max_by("chain", "step_no").alias("whole"))
            parts.append(whole.join(truth, ["qid", "whole"]).select(F.lit(name).alias("format"), "run", "qid", "split", "cand", "whole", F.col(column).alias("outcome")))
        return _union(parts)

    return bankrun.kept(spark, sf_dir, "formats", make)


@query()
def bank_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answer formats over all questions: mean accuracy of eight samples, and whether any of them is right."""
    f = _with_all(formats(spark, sf_dir), "split")
    each = f.groupBy("format", "split", "qid").agg(F.avg("outcome").alias("mean"), F.max("outcome").alias("best"))
    return each.groupBy("format", "split").agg(F.count("*").alias("questions"), (100 * F.avg("mean")).alias("accuracy"), (100 * F.avg("best")).alias("pass_at_8"))


@query()
def few_shot_outcomes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five-shot answers to the held-out questions: the chains of the nearest training questions, copied with their tables replaced by those that the question's words link to, and run."""
    from stepsql.operators.retrieve import copy_chain, nearest_examples
    from stepsql.operators.schema import link_score
    from stepsql.sources.tables import NAMES

    bank.prepare(spark, sf_dir)
    q = questions(spark)
    asked, seeds = q.where("split = 'held out'").select("qid", "question"), q.where("split = 'train'").select("qid", "question")
    near = nearest_examples(asked, seeds).collect()  # five rows a held-out question of the bank
    linked = link_score(asked.select(F.col("qid").cast("string").alias("qid"), "question"), spark.createDataFrame([(n,) for n in NAMES], "name string"))
    tables = {int(r.qid): r.names for r in linked.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("distance", "name"))).alias("names")).collect()}
    by = {x.qid: x for x in bank.QUESTIONS}
    rows = []
    for r in near:
        seed, gold = by[r.seed], by[r.qid]
        named, close = copy_chain(seed.named, seed.close, [x.name for x in tables.get(r.qid, [])], NAMES)
        want, got = run_text(spark, gold.gold), run_text(spark, compose(named, close))
        rows.append((r.qid, r.rank, r.seed, got["status"], int(got["status"] == "ok" and got["result_key"] == want["result_key"])))
    return spark.createDataFrame(rows, "qid bigint, rank int, seed bigint, status string, outcome int")


@query()
def bank_policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Policies of different quality, as temperatures of one policy: accuracy of one sample and of eight with selection."""
    done, base, s = runs(spark, sf_dir), policy(spark, sf_dir), scores(spark, sf_dir)
    heated = _union([base.withColumn("logit", F.col("logit") / t).withColumn("run", F.lit(f"temperature {t}")) for t in (0.5, 1.0, 2.0, 4.0)])
    c = written(bp.candidates(bp.rewarded(bp.scored_steps(bp.sample(heated, 8, 23), s, done))))
    return _union([ms.accuracy(bp.chosen(c, n, by), "run").select(F.col("run").alias("policy"), F.lit(name).alias("protocol"), "questions", "accuracy") for name, by, n in (("one sample", "first", 1), ("step reward@8", "reward", 8), ("pass@8", "any", 8))])


# --- robustness, sources, ablations, training ------------------------------------------------------------


@query()
def bank_robustness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy at eight candidates out of distribution: other wordings of the training questions, whose scores see other words, and the held-out databases; means by family."""
    done, labels = runs(spark, sf_dir), bp.prefix_labels(rollouts(spark, sf_dir), runs(spark, sf_dir))
    plain = bp.features(done, questions(spark)).where("split = 'train'")
    drawn = bp.sample(policy(spark, sf_dir), SearchConfig().candidates, 99)
    parts = []
    for style in ("knowledge", "synonym", "realistic"):
        # fitted on plain wordings, applied to the others
        other = bp.features(done, questions(spark, style)).withColumn("split", F.lit(style))
        s = bp.fit_scores(plain.unionByName(other), labels, done).join(other.select("qid", "chain"), ["qid", "chain"]).groupBy("qid", "chain").agg(F.first("score").alias("score"), F.first("orm").alias("orm"))
        c = bp.candidates(bp.rewarded(bp.scored_steps(drawn, s, done))).where("split = 'train'")
        parts.append(bp.chosen(c, 8, "reward").select(F.lit("robust").alias("family"), F.lit(style).alias("set_name"), "outcome"))
    parts.append(bp.chosen(sampled(spark, sf_dir).where("split = 'held out'"), 8, "reward").select(F.lit("cross").alias("family"), F.col("db").alias("set_name"), "outcome"))
    return ms.ood_rollup(_union(parts))


@query()
def source_sensitivity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of policies cold-started on each generator's corpus and on the mix, greedy and at eight candidates, with the spread over sources."""
    done, s = runs(spark, sf_dir), scores(spark, sf_dir)
    corpus = accepted(generated(spark, sf_dir), done)
    fitted = written(_union([bp.cold_start(menu(spark), corpus.where(F.col("run") == h.name), h.name) for h in (bp.Habits(), *bp.SOURCES)]))
    c = written(bp.candidates(bp.rewarded(bp.scored_steps(bp.sample(fitted, 8, 31), s, done))))
    rows = _union([ms.accuracy(greedy(spark, fitted, done), "run").withColumn("protocol", F.lit("greedy")), ms.accuracy(bp.chosen(c, 8, "reward"), "run").withColumn("protocol", F.lit("step reward@8"))])
    own = Window.partitionBy("protocol")
    return rows.select(F.col("run").alias("source"), "protocol", "accuracy", (F.max("accuracy").over(own) - F.min("accuracy").over(own)).alias("spread"), F.stddev_pop("accuracy").over(own).alias("deviation"))


@query()
def rl_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greedy and sampled accuracy by round with step rewards, with outcomes only and with partial credit, over three seeds."""
    return trained(spark, sf_dir)[1]


@query()
def bank_stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Final, mean, spread and peak of the sampled accuracy on training questions, and the round of convergence, by method and seed; mean and spread are those after the warm-up."""
    curve = trained(spark, sf_dir)[1].where("split = 'train' and protocol = 'sampled'").select(F.concat_ws("|", "method", "seed").alias("method"), "round", F.col("accuracy").alias("value"))
    return ms.stability(curve, TrainConfig().warm_up, 2.0)


@query()
def bank_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training by selector by split: a policy after its cold start, after outcome-only and after step-rewarded updates, decoded by each rule at eight candidates, and answer formats of the first."""
    done, s = runs(spark, sf_dir), scores(spark, sf_dir)
    policies = policy(spark, sf_dir).select(*bp.CONTEXT, "token", "error_type", "logit").unionByName(trained(spark, sf_dir)[0].where("run in ('step reward|17', 'outcome only|17')").select(*bp.CONTEXT, "token", "error_type", "logit"))
    drawn = written(bp.scored_steps(bp.sample(policies, 8, 61), s, done))
    parts = []
    for weighting, config in (("with certainty", RewardConfig(norm_scope="corpus")), ("without", RewardConfig(use_weight=False)), ("weights alone", RewardConfig(norm_scope="corpus", use_score=False))):
        c = written(bp.candidates(bp.rewarded(drawn, config)))
        rules = (("step reward", "reward"),) if weighting != "with certainty" else (("step reward", "reward"), ("outcome model", "orm"), ("self-consistency", "vote"), ("pass@n", "any"))
        parts += [bp.chosen(c, 8, by).select("run", F.lit(f"{name}, {weighting}" if name == "step reward" else name).alias("selector"), "split", "outcome") for name, by in rules]
    parts.append(greedy(spark, policies, done).select("run", F.lit("greedy").alias("selector"), "split", "outcome"))
    rows = _union(parts).select(F.lit("chain").alias("format"), F.split("run", r"\|")[0].alias("training"), "selector", "split", "outcome")
    other = formats(spark, sf_dir).where("format <> 'chain' and cand = 0").select("format", F.col("run").alias("training"), F.lit("one sample").alias("selector"), "split", "outcome")
    return ms.accuracy(_with_all(rows.unionByName(other), "split"), "format", "training", "selector", "split")


# --- errors -------------------------------------------------------------------------------------------


def failures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wrong answers at a budget of one and of eight with selection, over 32 candidates a question in groups of eight."""
    c = sampled(spark, sf_dir)
    group = (F.col("cand") / 8).cast("int")
    parts = []
    for name, n in (("one", 1), ("eight", 8)):
        some = c.withColumn("qid", F.concat_ws("#", "qid", group)).withColumn("cand", F.col("cand") % 8)
        parts.append(bp.chosen(some, n, "reward").withColumn("method", F.lit(name)))
    kinds = spark.createDataFrame(list(ms.TAXONOMY), "grp string, inferred string")
    return _union(parts).join(F.broadcast(kinds), "inferred", "left").withColumn("grp", F.coalesce("grp", F.lit("other")))  # the taxonomy: 16 rows


@query()
def bank_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Failures at both budgets by group and type, and their share of all answers."""
    f = failures(spark, sf_dir)
    total = f.groupBy("method").agg(F.count("*").alias("answers"))
    rolled = f.where("outcome = 0").rollup("method", "grp", "inferred").agg(F.count("*").alias("errors")).where("method is not null")
    return rolled.join(total, "method").select("method", F.coalesce("grp", F.lit("(all)")).alias("grp"), F.coalesce("inferred", F.lit("(all)")).alias("error_type"), "errors", (100 * F.col("errors") / F.col("answers")).alias("share"))


@query()
def bank_error_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Change of failures from one candidate to eight, by type and in all, with the relative reduction."""
    f = failures(spark, sf_dir).where("outcome = 0").select("method", F.col("inferred").alias("error_type"))
    return ms.error_delta(_with_all(f, "error_type"), "one", "eight")


@query()
def bank_step_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Audit of up to 200 failed candidates by what their executed steps show: rows lost against gold's step, a needless step, a step that does another's work, or nothing to do with steps."""
    done, c = runs(spark, sf_dir), sampled(spark, sf_dir)
    failed = c.where("outcome = 0").select("question", "whole", "cand").orderBy(F.md5(F.concat_ws("-", "question", "whole", "cand")), "question", "cand").limit(SearchConfig().failure_sample)
    gold = done.where("slips = 0").select("qid", "slot", F.col("n_rows").alias("gold_rows"), F.col("n_cols").alias("gold_cols"))
    own = redundant(spark, sf_dir).select("qid", "whole", "slot", "redundant")
    s = done.select("qid", "whole", "slot", "slots", "n_rows", "n_cols", "status").join(gold, ["qid", "slot"]).join(own, ["qid", "whole", "slot"]).where("slot < slots")
    chain = s.groupBy("qid", "whole").agg(
        F.max(F.when((F.col("status") == "ok") & (F.col("n_rows") < F.col("gold_rows")), 1).otherwise(0)).alias("lost"), F.max(F.col("redundant").cast("int")).alias("redundant_steps"),
        F.max(F.when((F.col("status") == "ok") & ((F.col("n_cols") != F.col("gold_cols")) | (F.col("n_rows") > F.col("gold_rows"))), 1).otherwise(0)).alias("merged_steps"),
    )
    cases = failed.join(chain, (F.col("question") == F.col("qid")) & (failed["whole"] == chain["whole"]), "left").select(
        F.concat_ws("-", "question", "cand").alias("traj_id"), F.lit(1).alias("gold_rows"), (1 - F.coalesce("lost", F.lit(0))).alias("kept_rows"), F.coalesce("redundant_steps", F.lit(0)).alias("redundant_steps"), F.coalesce("merged_steps", F.lit(0)).alias("merged_steps")
    )
    return ch.chain_error(cases).groupBy("category").agg(F.count("*").alias("chains"))


# --- redundancy ---------------------------------------------------------------------------------------


def redundant(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five rules on every executed chain of the menus."""
    return bankrun.kept(spark, sf_dir, "redundant", lambda: ch.redundant_steps(runs(spark, sf_dir)))


@query()
def bank_redundancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Up to 500 sampled chains, by whether a step is redundant: how many, mean step entropy, mean weight under one shared normaliser, accuracy."""
    flags = redundant(spark, sf_dir).groupBy(F.col("qid").alias("question"), "whole").agg(F.bool_or("redundant").alias("redundant"))
    c = sampled(spark, sf_dir).orderBy(F.md5(F.concat_ws("-", "question", "cand")), "question", "cand").limit(SearchConfig().redundancy_sample).join(flags, ["question", "whole"])
    both = c.crossJoin(F.broadcast(c.agg(F.max("entropy").alias("top"))))  # one row
    return both.groupBy("redundant").agg(F.count("*").alias("chains"), F.avg("entropy").alias("mean_entropy"), F.avg(F.when(F.col("top") > 0, 1 - F.col("entropy") / F.col("top")).otherwise(F.lit(1.0))).alias("mean_weight"), (100 * F.avg("outcome")).alias("accuracy"))


@query()
def bank_redundancy_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps that each rule flags, over all executed chains."""
    rules = ("repeats_result", "duplicate_join", "idle_filter", "unreferenced", "keeps_all_rows")
    return redundant(spark, sf_dir).select(F.inline(F.array(*[F.struct(F.lit(r).alias("rule"), F.col(r).cast("int").alias("hit")) for r in rules]))).groupBy("rule").agg(F.sum("hit").alias("steps"), F.count("*").alias("of"))


# --- latency, frontier, runtime ------------------------------------------------------------------------


def timings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """n, stage, seconds: chains are drawn and scored under the clock; executing n of them takes what their distinct runs took."""

    def make() -> DataFrame:
        done, s, own = runs(spark, sf_dir), scores(spark, sf_dir), policy(spark, sf_dir)
        spent = done.groupBy("qid", "chain").agg(F.first("seconds").alias("seconds"), F.first("run_key").alias("run_key"))
        rows = []
        for n in BUDGETS:
            began = time.perf_counter()
            drawn = written(bp.sample(own, n, 99))
            rows.append((n, "generate", time.perf_counter() - began))
            executed = drawn.select("qid", "chain").distinct().join(spent, ["qid", "chain"]).select("run_key", "seconds").distinct()
            rows.append((n, "execute", executed.agg(F.sum("seconds").alias("s")).first().s))
            began = time.perf_counter()
            bp.candidates(bp.rewarded(bp.scored_steps(drawn, s, done))).write.format("noop").mode("overwrite").save()
            rows.append((n, "score", time.perf_counter() - began))
        return spark.createDataFrame(rows, "n int, stage string, seconds double")

    return bankrun.kept(spark, sf_dir, "timings", make)


@query()
def latency_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of generating, executing and scoring 1 to 32 chains a question, and their shares."""
    return ms.latency_breakdown(timings(spark, sf_dir))


@query()
def bank_pareto(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Protocols that no faster one matches in accuracy, greedy decoding among them: latency is what a protocol's stages take a question."""
    t, asked = timings(spark, sf_dir), len(bank.QUESTIONS)
    spent = t.groupBy("n").agg(F.sum(F.when(F.col("stage") == "generate", F.col("seconds"))).alias("g"), F.sum(F.when(F.col("stage") == "execute", F.col("seconds"))).alias("x"), F.sum(F.when(F.col("stage") == "score", F.col("seconds"))).alias("s"))
    a = ms.accuracy(_methods(spark, sf_dir).where("method <> 'pass@n'"), "method", "n").join(spent, "n")
    # greedy and votes need no score
    cost = F.col("g") + F.when(F.col("method") == "greedy", F.lit(0.0)).otherwise(F.col("x")) + F.when(F.col("method").isin("greedy", "self-consistency"), F.lit(0.0)).otherwise(F.col("s"))
    return sel.pareto(a.select("method", "n", "accuracy", (cost / asked).alias("seconds")), "seconds", "accuracy")


@query()
def chain_vs_flat_runtime(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Median seconds of every question's chain, of its flat form and of the gold query over cold repeats, results drained, and the chain's overhead over gold in percent."""
    bank.prepare(spark, sf_dir)
    rows = []
    for q in bank.QUESTIONS:
        for k in range(SearchConfig().runtime_repeats):
            for name, text in (("chain", compose(q.named, q.close)), ("flat", flatten(q.named, q.close)), ("gold", q.gold)):
                spark.catalog.clearCache()
                began = time.perf_counter()
                spark.sql(text).write.format("noop").mode("overwrite").save()
                rows.append((q.qid, q.tier, name, k, time.perf_counter() - began))
    t = spark.createDataFrame(rows, "qid bigint, tier string, form string, k int, seconds double").groupBy("qid", "tier").agg(
        *[F.percentile(F.when(F.col("form") == f, F.col("seconds")), 0.5).alias(f) for f in ("chain", "flat", "gold")]
    )
    return t.withColumn("overhead", 100 * (F.col("chain") / F.col("gold") - 1))


# --- search --------------------------------------------------------------------------------------------


@query()
def mc_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Success labels of the bank's prefixes from six rounds of each search rule."""
    done, own = runs(spark, sf_dir), policy(spark, sf_dir)
    return bp.search_tree(own, done, 6)


@query()
def beam_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains of the bank grown step by step under step rewards, two kept a question, with their outcomes."""
    done = runs(spark, sf_dir)
    return bp.beam(policy(spark, sf_dir), scores(spark, sf_dir)).join(done.where("slot = slots").select("qid", "chain", "split", "outcome"), ["qid", "chain"])
