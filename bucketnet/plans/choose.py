"""Which physical plan a training step takes, from sizes alone."""

from __future__ import annotations

from dataclasses import dataclass

from bucketnet.plans.blocks import SNAPSHOT_LIMIT

RELATIONAL_PAIRS = 1 << 22


@dataclass(frozen=True)
class Sizes:
    features: int
    hidden: int
    labels: int
    batch: int
    active: int

    @property
    def snapshot(self) -> int:
        """Bytes of weights and two moments in single precision."""
        return 12 * self.hidden * (self.features + self.labels)

    @property
    def pairs(self) -> int:
        """Products of a step if (instance, neuron, weight) became rows."""
        return self.batch * self.active * self.hidden


def choose(sizes: Sizes, limit: int = SNAPSHOT_LIMIT) -> str:
    """relational (A) where its rows are few, blocks (B) while a snapshot can be broadcast, shards (C) beyond."""
    if sizes.pairs <= RELATIONAL_PAIRS and sizes.snapshot <= 1 << 26:
        return "relational"
    return "blocks" if sizes.snapshot <= limit else "shards"


def sampling_strategy(beta: int, mean_candidates: float, quality_first: bool) -> str:
    """vanilla is cheapest and its sample worst; threshold needs no sort; top-k holds the budget exactly."""
    if not quality_first:
        return "vanilla"
    return "topk" if mean_candidates > 2 * beta else "threshold"
