"""Count-based next-token policies: for this family, counting is the maximum-likelihood fit."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def fit_policy(tokens: DataFrame, context: tuple[str, ...] = ("prev",), alpha: float = 0.0) -> DataFrame:
    """context..., token, n, p from tokens; alpha adds to each count over the tokens seen anywhere. Rows grow with
    distinct (context, token) pairs, not with tokens."""
    counts = tokens.groupBy(*context, "token").agg(F.count("*").alias("n"))
    own = Window.partitionBy(*context) if context else None
    whole = F.sum("n").over(own) if own is not None else None
    if own is None:
        return counts.crossJoin(F.broadcast(counts.agg(F.sum("n").alias("all")))).select("token", "n", (F.col("n") / F.col("all")).alias("p"))  # one row
    if alpha == 0:
        return counts.withColumn("p", F.col("n") / whole)
    size = counts.agg(F.count_distinct("token").alias("v"))
    return counts.crossJoin(F.broadcast(size)).withColumn("p", (F.col("n") + alpha) / (whole + alpha * F.col("v"))).drop("v")  # one row


def policy_entropy(policy: DataFrame, context: tuple[str, ...] = ("prev",)) -> DataFrame:
    """context..., entropy in nats of each context's distribution."""
    return policy.groupBy(*context).agg((-F.sum(F.col("p") * F.ln("p"))).alias("entropy"))


def nll(tokens: DataFrame, policy: DataFrame, context: tuple[str, ...] = ("prev",), floor: float = 1e-9) -> DataFrame:
    """One row: tokens, loss (sum of -ln p), mean_loss; tokens the policy has never seen get the floor."""
    joined = tokens.join(policy.select(*context, "token", "p"), [*context, "token"], "left")
    cost = -F.ln(F.coalesce("p", F.lit(floor)))
    return joined.agg(F.count("*").alias("tokens"), F.sum(cost).alias("loss"), F.avg(cost).alias("mean_loss"))


def exact_kl(policy: DataFrame, reference: DataFrame, context: tuple[str, ...] = ("prev",)) -> DataFrame:
    """context..., kl: sum of p ln(p / q), where reference has token and p (of any context)."""
    q = reference.select("token", F.col("p").alias("q"))
    return policy.join(q, "token").groupBy(*context).agg(F.sum(F.col("p") * F.ln(F.col("p") / F.col("q"))).alias("kl"))


def greedy(policy: DataFrame, context: tuple[str, ...] = ("prev",)) -> DataFrame:
    """context..., token, p: the likeliest token, ties to the first by name."""
    order = Window.partitionBy(*context).orderBy(F.desc("n"), "token")
    return policy.withColumn("r", F.row_number().over(order)).where("r = 1").select(*context, "token", "p")


def uniform(*parts, seed: int = 17):
    """A number in [0, 1) from a hash of the parts: the same on any partitioning, unlike rand()."""
    return F.pmod(F.xxhash64(F.lit(seed), *parts), F.lit(1 << 52)) / F.lit(float(1 << 52))


def sample_tokens(asks: DataFrame, policy: DataFrame, context: tuple[str, ...] = ("prev",), temperature: float = 1.0) -> DataFrame:
    """asks (context..., u in [0, 1)) with token: the first token, by name, whose cumulated probability passes u."""
    own = Window.partitionBy(*context)
    heat = policy.withColumn("q", F.pow("p", F.lit(1.0 / temperature)))
    heat = heat.withColumn("q", F.col("q") / F.sum("q").over(own))
    steps = heat.withColumn("hi", F.sum("q").over(own.orderBy("token").rowsBetween(Window.unboundedPreceding, 0)))
    table = steps.groupBy(*context).agg(F.array_sort(F.collect_list(F.struct("hi", "token"))).alias("table"))
    drawn = F.filter("table", lambda x: x["hi"] > F.col("u"))
    picked = F.coalesce(F.get(drawn, F.lit(0)), F.element_at("table", -1))
    return asks.join(table, list(context)).withColumn("token", picked["token"]).drop("table")


def sample_chains(policy: DataFrame, questions: DataFrame, n: int, length: int, temperature: float = 1.0, seed: int = 17, start: str = "^") -> DataFrame:
    """qid, cand, tokens: n chains a question, drawn token by token from an order-2 policy. The loop runs over the
    length, all chains side by side."""
    state = questions.select("qid", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("cand"), F.lit(start).alias("prev"), F.array().cast("array<string>").alias("tokens"))
    for at in range(length):
        asks = state.withColumn("u", uniform("qid", "cand", F.lit(at), seed=seed))
        drawn = sample_tokens(asks, policy, temperature=temperature)
        state = drawn.select("qid", "cand", F.col("token").alias("prev"), F.concat("tokens", F.array("token")).alias("tokens"))
    return state.drop("prev")
