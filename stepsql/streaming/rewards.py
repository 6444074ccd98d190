"""Streams of rollout logs and of events."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from stepsql.sources.shared import new_folder


def stream_of(spark: SparkSession, path: str, schema: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what its source holds; the rows that it appended."""
    spark, out = stream.sparkSession, new_folder(stream.sparkSession)
    q = stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", f"{out}-state").option("path", out).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def drain_table(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """The same for streams that revise rows: the last batch written stands."""
    spark, out = stream.sparkSession, new_folder(stream.sparkSession)
    q = (
        stream.writeStream.outputMode(mode).option("checkpointLocation", f"{out}-state").trigger(availableNow=True)
        .foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).start()
    )
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def reward_stream(steps: DataFrame, h_max: float) -> DataFrame:
    """qid, traj_id, step_no, prefix_score, reward as steps arrive, in step order within a trajectory, under a fixed normaliser: the state of a
    trajectory is (entropy, weight sum, weighted scores, scores, count, reward)."""

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        h, den, num, plain, n, acc = state.get if state.exists else (0.0, 0.0, 0.0, 0.0, 0, 0.0)
        new = pd.concat(list(parts)).sort_values("step_no")
        entropy = h + new.h_step.cumsum().to_numpy()
        weight = 1 - entropy / h_max if h_max > 0 else np.ones(len(new))
        score = new.score.to_numpy()
        mass, weighted, sums, counts = den + weight.cumsum(), num + (weight * score).cumsum(), plain + score.cumsum(), n + np.arange(1, len(new) + 1)
        prefix = np.where(mass > 0, weighted / np.where(mass > 0, mass, 1.0), sums / counts)
        reward = acc + prefix.cumsum()
        state.update(tuple(map(float, (entropy[-1], mass[-1], weighted[-1], sums[-1]))) + (int(counts[-1]), float(reward[-1])))
        yield pd.DataFrame({"qid": key[0], "traj_id": key[1], "step_no": new.step_no.to_numpy(), "prefix_score": prefix, "reward": reward})

    return steps.groupBy("qid", "traj_id").applyInPandasWithState(
        run, "qid bigint, traj_id bigint, step_no int, prefix_score double, reward double", "h double, den double, num double, plain double, n bigint, acc double", "append", GroupStateTimeout.NoTimeout
    )


def drain_rewards(steps: DataFrame, h_max: float) -> DataFrame:
    """The rows of reward_stream, by running sums over each batch: what a trajectory holds so far is a row of a table that each batch reads and writes anew, so a
    trajectory costs no call of its own. A batch that is run again writes the same tables again."""
    spark, out = steps.sparkSession, new_folder(steps.sparkSession)
    key = ["qid", "traj_id"]
    held = "qid bigint, traj_id bigint, h double, den double, num double, plain double, n bigint, acc double"
    run = Window.partitionBy(*key).orderBy("step_no").rowsBetween(Window.unboundedPreceding, 0)
    so_far = lambda name, c: F.coalesce(name, F.lit(0)) + F.sum(c).over(run)

    def step(batch: DataFrame, k: int) -> None:
        before = batch.sparkSession.read.schema(held).parquet(f"{out}-held/{k - 1}") if k else batch.sparkSession.createDataFrame([], held)
        rows = batch.join(before, key, "left").withColumn("h", so_far("h", "h_step"))
        rows = rows.withColumn("w", 1 - F.col("h") / h_max if h_max > 0 else F.lit(1.0))
        rows = rows.withColumns({"den": so_far("den", "w"), "num": so_far("num", F.col("w") * F.col("score")), "plain": so_far("plain", "score"), "n": so_far("n", F.lit(1))})
        rows = rows.withColumn("prefix_score", F.when(F.col("den") > 0, F.col("num") / F.col("den")).otherwise(F.col("plain") / F.col("n"))).withColumn("acc", so_far("acc", "prefix_score"))
        fields = ["h", "den", "num", "plain", "n", "acc"]
        rows.select(*key, "step_no", "prefix_score", F.col("acc").alias("reward"), *fields).write.mode("overwrite").parquet(f"{out}/batch={k}")
        new = batch.sparkSession.read.parquet(f"{out}/batch={k}").groupBy(*key).agg(F.max(F.struct("step_no", *fields)).alias("s")).select(*key, *[f"s.{c}" for c in fields])
        new.unionByName(before.join(new, key, "left_anti")).write.mode("overwrite").parquet(f"{out}-held/{k}")

    steps.writeStream.option("checkpointLocation", f"{out}-state").trigger(availableNow=True).foreachBatch(step).start().awaitTermination()
    return spark.read.schema("qid bigint, traj_id bigint, step_no int, prefix_score double, reward double, batch int").parquet(out).drop("batch")


def split_log(log: DataFrame, by: str, parts: int = 3, key: tuple[str, ...] = (), files: int = 1) -> str:
    """A folder of Parquet files that a file stream reads in order of `by`. With a key, each part is up to so many files, and rows of one key share a file of a
    part: their order holds however many files a batch takes."""
    path = new_folder(log.sparkSession)
    edges = log.agg(F.min(by).alias("a"), F.max(by).alias("b")).first()
    for k in range(parts):
        lo, hi = edges.a + (edges.b - edges.a) / parts * k, edges.a + (edges.b - edges.a) / parts * (k + 1)
        piece = log.where((F.col(by) >= F.lit(lo)) & ((F.col(by) < F.lit(hi)) if k < parts - 1 else F.lit(True)))
        (piece.repartition(files, *key) if key else piece.coalesce(1)).write.mode("append").parquet(path)
    return path
