"""Monte-Carlo success labels over a prefix tree.

All completions are known, so a completion adds to every prefix of its own: explode, sum digests along the completion and
aggregate, with no walk from the leaves up."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def visits(rollouts: DataFrame, *carry: str) -> DataFrame:
    """qid, traj_id, depth, prefix_key, parent_key, leaf, outcome (and columns named by carry) from qid, traj_id, steps, outcome: a row
    for each prefix of each completion.

    Each step's own digest, place included, is four words; a prefix is named by their running sums, so a row carries its own key and its
    parent's, and a completion of any length costs its length. Null steps count as empty."""
    lines = rollouts.select("qid", "traj_id", "outcome", *carry, F.size("steps").alias("n"), F.posexplode("steps").alias("at", "step"))
    own = F.md5(F.concat_ws("\x1f", F.col("at").cast("string"), F.coalesce("step", F.lit(""))))
    words = [f"w{i}" for i in range(4)]
    hashed = lines.withColumn("own", own).select(
        "qid", "traj_id", "outcome", *carry, "n", "at", *[F.conv(F.substring("own", 8 * i + 1, 8), 16, 10).cast("bigint").alias(w) for i, w in enumerate(words)]
    )
    chain = Window.partitionBy("qid", "traj_id").orderBy("at")
    run = chain.rowsBetween(Window.unboundedPreceding, 0)
    keyed = hashed.withColumn("prefix_key", F.md5(F.concat_ws("-", *[F.sum(w).over(run).cast("string") for w in words])))
    return keyed.select(
        "qid", "traj_id", (F.col("at") + 1).alias("depth"), "prefix_key", F.lag("prefix_key").over(chain).alias("parent_key"), (F.col("at") + 1 == F.col("n")).alias("leaf"), "outcome", *carry
    )


def prefix_tree(rollouts: DataFrame) -> DataFrame:
    """qid, prefix_key, parent_key, depth, visits, wins, sigma: one row a node."""
    return visits(rollouts).groupBy("qid", "prefix_key", "parent_key", "depth").agg(
        F.count("*").alias("visits"), F.sum("outcome").cast("bigint").alias("wins"), F.avg("outcome").alias("sigma")
    )


def weighted_sigma(rollouts: DataFrame, logp: str = "logp") -> DataFrame:
    """qid, prefix_key, sigma: success under the policy's own probabilities of the distinct completions."""
    whole = rollouts.withColumn("leaf_key", F.md5(F.array_join("steps", "\x1f", "")))
    once = visits(whole, "leaf_key", logp).groupBy("qid", "prefix_key", "leaf_key").agg(F.max(logp).alias("lp"), F.max("outcome").alias("r"))
    p = F.exp("lp")
    return once.groupBy("qid", "prefix_key").agg((F.sum(p * F.col("r")) / F.sum(p)).alias("sigma"))


def path_diversity(rollouts: DataFrame) -> DataFrame:
    """qid, completions, paths, duplicate_share: distinct root-to-leaf paths."""
    leaf = F.md5(F.array_join("steps", "\x1f"))
    return rollouts.groupBy("qid").agg(F.count("*").alias("completions"), F.count_distinct(leaf).alias("paths")).withColumn(
        "duplicate_share", 1 - F.col("paths") / F.col("completions")
    )
