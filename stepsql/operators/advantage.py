"""Group-standardised step advantages and the clipped objective."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .reward import TRAJECTORY


def raw(rewarded: DataFrame, use_step: bool = True) -> DataFrame:
    """Adds adv_raw: outcome plus the prefix scores from this step to the end."""
    onward = Window.partitionBy(*TRAJECTORY).orderBy("step_no").rowsBetween(0, Window.unboundedFollowing)
    to_go = F.sum("prefix_score").over(onward) if use_step else F.lit(0.0)
    return rewarded.withColumn("adv_raw", F.col("outcome") + to_go)


def standardise(steps: DataFrame, std: str = "pop", unit: str = "step") -> DataFrame:
    """Adds adv: adv_raw less its mean over the question's group, over its deviation; 0 where that is 0.

    unit `token` counts each step once for every token. The group's moments come from a combined aggregate, not from a
    window, as groups may be large."""
    n = F.col("n_tokens").cast("double") if unit == "token" else F.lit(1.0)
    x = F.col("adv_raw")
    # squares about the mean: from Spark's own moment for steps, from weighted sums for tokens
    squares = F.var_pop(x) * F.count(x) if unit == "step" else F.greatest(F.sum(n * x * x) - F.sum(n * x) * F.sum(n * x) / F.sum(n), F.lit(0.0))
    moments = steps.groupBy("qid").agg(F.sum(n).alias("n_"), (F.sum(n * x) / F.sum(n)).alias("mean_"), squares.alias("q_"), F.min(x).alias("low_"), F.max(x).alias("high_"))
    joined = steps.join(moments, "qid")
    freedom = F.col("n_") - (1 if std == "sample" else 0)
    flat = (F.col("high_") == F.col("low_")) | (freedom <= 0)
    adv = F.when(flat, F.lit(0.0)).otherwise((x - F.col("mean_")) / F.sqrt(F.col("q_") / freedom))
    return joined.withColumn("adv", adv).drop("n_", "q_", "mean_", "low_", "high_")


def ratio(base: str = "ref") -> Column:
    """Probability ratio of a token against the reference (`ref`) or the sampling (`old`) policy."""
    return F.exp(F.col("logp") - F.col({"ref": "logp_ref", "old": "logp_old"}[base]))


def surrogate(rho: Column, adv: Column, clip: float = 0.2) -> Column:
    return F.least(rho * adv, F.least(F.greatest(rho, F.lit(1 - clip)), F.lit(1 + clip)) * adv)


def kl(kind: str = "k3", logp: Column | None = None, logp_ref: Column | None = None) -> Column:
    """Per-token estimators of the divergence from the reference policy: k1, k2 (half the square) and the non-negative k3."""
    d = (F.col("logp_ref") if logp_ref is None else logp_ref) - (F.col("logp") if logp is None else logp)
    return {"k1": -d, "k2": d * d / 2, "k3": F.exp(d) - d - 1}[kind]


def group_loss(tokens: DataFrame, clip: float = 0.2, penalty: float = 0.02, base: str = "ref", final_tokens: str | None = None) -> DataFrame:
    """qid, loss, kl from tokens with qid, traj_id, logp, logp_ref, adv: each trajectory's surrogate sum over its token count
    (with those of the closing query, if a column of that name is given), then the mean over the group, less the penalty."""
    rho = ratio(base)
    extra = F.max(final_tokens) if final_tokens else F.lit(0)
    chains = tokens.groupBy(*TRAJECTORY).agg(
        (F.sum(surrogate(rho, F.col("adv"), clip)) / (F.count("*") + extra)).alias("term"), F.avg(kl("k3")).alias("kl")
    )
    return chains.groupBy("qid").agg((F.avg("term") - penalty * F.avg("kl")).alias("loss"), F.avg("kl").alias("kl"))


def objective(rewards: DataFrame, kl_by_chain: DataFrame, penalty: float = 0.02) -> DataFrame:
    """One row, objective: mean of step reward plus outcome less the penalty times the divergence."""
    both = rewards.join(kl_by_chain, list(TRAJECTORY))
    return both.agg(F.avg(F.col("reward") + F.col("outcome") - penalty * F.col("kl")).alias("objective"), F.count("*").alias("chains"))


def pair_loss(chains: DataFrame, beta: float = 0.1) -> DataFrame:
    """qid, loss of the preference objective: best against worst trajectory of a question by reward, ties by traj_id."""
    ends = chains.groupBy("qid").agg(
        F.max(F.struct("reward", "traj_id", (F.col("logp") - F.col("logp_ref")).alias("d"))).alias("best"),
        F.min(F.struct("reward", "traj_id", (F.col("logp") - F.col("logp_ref")).alias("d"))).alias("worst"),
    )
    gap = F.col("best.d") - F.col("worst.d")
    return ends.where("best.traj_id <> worst.traj_id").select("qid", F.ln(1 + F.exp(-beta * gap)).alias("loss"))
