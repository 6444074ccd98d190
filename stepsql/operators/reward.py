"""Certainty weights and step rewards.

Flat logs use running windows, all partitioned by trajectory, so that one exchange (none on a log bucketed by
question and trajectory) serves them; logs stored one row a chain use the nested form, which does not shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stepsql.config import RewardConfig

TRAJECTORY = ("qid", "traj_id")


def _running():
    return Window.partitionBy(*TRAJECTORY).orderBy("step_no").rowsBetween(Window.unboundedPreceding, 0)


def prefix_entropy(steps: DataFrame, mode: str = "cumulative") -> DataFrame:
    """Adds h_prefix."""
    forms = {"cumulative": F.sum("h_step").over(_running()), "step": F.col("h_step"), "mean_prefix": F.avg("h_step").over(_running())}
    return steps.withColumn("h_prefix", forms[mode])


def certainty_weight(steps: DataFrame, config: RewardConfig = RewardConfig()) -> DataFrame:
    """Adds h_prefix, h_max and w = 1 - h_prefix / h_max (1 where the largest entropy is 0)."""
    if not config.use_weight:
        return steps.withColumn("w", F.lit(1.0))
    steps = prefix_entropy(steps, config.entropy_mode)
    if config.norm_scope == "trajectory":
        steps = steps.withColumn("h_max", F.max("h_prefix").over(Window.partitionBy(*TRAJECTORY)))
    elif config.norm_scope == "group":
        # an aggregate with map-side combining and a join, as a group may be any size
        steps = steps.join(steps.groupBy("qid").agg(F.max("h_prefix").alias("h_max")), "qid")
    else:
        steps = steps.crossJoin(F.broadcast(steps.agg(F.max("h_prefix").alias("h_max"))))  # one row
    return steps.withColumn("w", F.when(F.col("h_max") > 0, 1 - F.col("h_prefix") / F.col("h_max")).otherwise(F.lit(1.0)))


def step_reward(steps: DataFrame, config: RewardConfig = RewardConfig()) -> DataFrame:
    """Adds w, prefix_score and reward to a log with qid, traj_id, step_no, score, h_step.

    prefix_score is the weighted mean of the scores so far (their plain mean where all weights so far are 0);
    reward accumulates it. Without include_final the last step of each trajectory is left out."""
    if not config.include_final:
        last = F.max("step_no").over(Window.partitionBy(*TRAJECTORY))
        steps = steps.withColumn("last", last).where("step_no < last").drop("last")
    return accumulate(certainty_weight(steps, config), config)


def accumulate(weighted: DataFrame, config: RewardConfig = RewardConfig()) -> DataFrame:
    """The second half of step_reward, for steps that have their weight w already."""
    scored = weighted
    s = F.col("score") if config.use_score else F.lit(1.0)
    run = _running()
    mass = F.sum("w").over(run)
    scored = scored.withColumn("prefix_score", F.when(mass > 0, F.sum(F.col("w") * s).over(run) / mass).otherwise(F.avg(s).over(run)))
    return scored.withColumn("reward", {"sum": F.sum("prefix_score").over(run), "mean": F.avg("prefix_score").over(run), "last": F.col("prefix_score")}[config.agg])


def trajectory_reward(rewarded: DataFrame) -> DataFrame:
    """qid, traj_id, n_steps, reward, outcome: the last step's reward of each trajectory."""
    return rewarded.groupBy(*TRAJECTORY).agg(
        F.max("step_no").cast("int").alias("n_steps"), F.max_by("reward", "step_no").alias("reward"), F.max("outcome").alias("outcome")
    )


def nest(steps: DataFrame) -> DataFrame:
    """One row a trajectory, steps an array in step order."""
    fields = [c for c in ("step_no", "score", "h_step", "n_tokens") if c in steps.columns]
    return steps.groupBy(*TRAJECTORY).agg(F.array_sort(F.collect_list(F.struct(*fields))).alias("steps"), F.max("outcome").alias("outcome"))


def nested_reward(steps: Column, h_max: Column | None = None) -> Column:
    """Final reward of an array of steps with score and h_step, cumulative entropies: a fold with state (entropy,
    weight sum, weighted scores, scores, count, reward). h_max defaults to the trajectory's own largest."""
    top = F.aggregate(steps, F.lit(0.0), lambda a, x: a + x["h_step"]) if h_max is None else h_max
    start = F.struct(*[F.lit(0.0).alias(c) for c in ("h", "den", "num", "plain", "n", "reward")])

    def fold(a: Column, x: Column) -> Column:
        h = a["h"] + x["h_step"]
        w = F.when(top > 0, 1 - h / top).otherwise(F.lit(1.0))
        den, num, plain, n = a["den"] + w, a["num"] + w * x["score"], a["plain"] + x["score"], a["n"] + 1.0
        score = F.when(den > 0, num / den).otherwise(plain / n)
        return F.struct(h.alias("h"), den.alias("den"), num.alias("num"), plain.alias("plain"), n.alias("n"), (a["reward"] + score).alias("reward"))

    return F.aggregate(steps, start, fold, lambda a: a["reward"])


def graded_outcome(outcome: Column, ran: Column, partial: float = 0.1) -> Column:
    """Outcome reward with partial credit: 1 if right, `partial` if the query ran, 0 if it failed (or is unknown)."""
    return F.when(outcome == 1, F.lit(1.0)).when(ran, F.lit(partial)).otherwise(F.lit(0.0))
