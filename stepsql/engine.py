"""The engine as one object."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from stepsql.config import RewardConfig, TrainConfig
from stepsql.operators import bankpolicy, execute, labels, measures, reward, select
from stepsql.sources import bank


class Engine:
    """Step chains over one set of tables."""

    def __init__(self, spark: SparkSession):
        self.spark = spark

    def register(self, sf_dir: str) -> "Engine":
        bank.prepare(self.spark, sf_dir)
        return self

    def run(self, steps: list[tuple[str, str]], close: str) -> DataFrame:
        """Digests of every prefix of one chain."""
        return execute.run_chains(self.spark, [(steps, close)])

    def score(self, log: DataFrame, config: RewardConfig = RewardConfig()) -> DataFrame:
        return reward.step_reward(log, config)

    def select(self, cands: DataFrame, n: int = 8, by: str = "reward") -> DataFrame:
        return select.majority_vote(cands, n) if by == "vote" else select.best_of_n(cands, n, by)

    def labels(self, rollouts: DataFrame) -> DataFrame:
        return labels.prefix_tree(rollouts)

    def train(self, start: DataFrame, scores: DataFrame, runs: DataFrame, config: TrainConfig = TrainConfig()) -> tuple[DataFrame, DataFrame]:
        """(policies, curve) of the step-rewarded and the outcome-only update from one cold-started policy."""
        return bankpolicy.train(start, (f"step reward|{config.seed}", f"outcome only|{config.seed}"), scores, runs, config)

    def evaluate(self, outcomes: DataFrame, *by: str) -> DataFrame:
        return measures.accuracy(outcomes, *by)
