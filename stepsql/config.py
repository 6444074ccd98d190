"""Settings with the values that the literature reports as defaults."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class RewardConfig:
    """How step rewards are formed.

    entropy_mode: `cumulative` (running sum of step entropies), `step` (the step's own), `mean_prefix` (running mean).
    norm_scope: the prefixes among which the largest entropy is sought: `trajectory`, `group` (question), `corpus`.
    agg: `sum` of prefix scores up to a step, their `mean`, or the `last` one.
    """

    entropy_mode: str = "cumulative"
    norm_scope: str = "trajectory"
    agg: str = "sum"
    include_final: bool = True
    use_weight: bool = True
    use_score: bool = True

    def __post_init__(self) -> None:
        for name, value, allowed in (
            ("entropy_mode", self.entropy_mode, ("cumulative", "step", "mean_prefix")),
            ("norm_scope", self.norm_scope, ("trajectory", "group", "corpus")),
            ("agg", self.agg, ("sum", "mean", "last")),
        ):
            if value not in allowed:
                raise ValueError(f"{name} is one of {allowed}, not {value!r}")


@dataclass(frozen=True)
class TrainConfig:
    group: int = 8
    clip: float = 0.2
    kl: float = 0.02
    temperature: float = 1.0
    rounds: int = 60
    rate: float = 0.5
    warm_up: int = 50
    seed: int = 17
    use_step: bool = True
    ratio_base: str = "old"
    inner: int = 2  # gradient steps on one sampled group
    sharing: float = 0.5  # how much of a step goes to all options of the same kind


@dataclass(frozen=True)
class SearchConfig:
    """Defaults of sampling and selection, as reported: kept in one place, used where named."""

    samples_per_question: int = 3
    rollouts: int = 8
    label_rollouts: int = 32  # completions a question that success labels are formed from
    candidates: int = 8
    budgets: tuple[int, ...] = (1, 2, 4, 8, 16, 32)
    redundancy_sample: int = 500
    failure_sample: int = 200
    runtime_repeats: int = 5


@dataclass(frozen=True)
class SftConfig:
    """Recorded defaults of the maximum-likelihood fit; counting has no learning rate."""

    rate: float = 1e-5
    batch: int = 64
    context: int = 4096
    epochs: int = 3
