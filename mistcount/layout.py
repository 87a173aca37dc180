"""Shapes of bitmap sketches: how many cells there are, and how likely an item falls into each.

A layout numbers cells from 0; cell = bucket * levels + level - 1. All cells of a level are equally
likely, so a sketch's level counts hold all that an estimator needs.
"""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Layout:
    """Buckets by levels; level j holds an item with probability 2^-j, the last level takes the tail."""

    buckets: int = 4096
    levels: int = 24
    seed: int = 0
    family: str = "xxhash64"  # or md5, which other engines have too

    kind = "pcsa"
    #: Cells that one item sets at most: the sensitivity that a budget is divided by.
    hashes = 1

    @property
    def cells(self) -> int:
        return self.buckets * self.levels

    def rho(self) -> list[float]:
        """Probability that an item falls into a given cell, by level."""
        return [2.0 ** -min(j, self.levels - 1) / self.buckets for j in range(1, self.levels + 1)]

    def most(self) -> float:
        """Cardinality at which the last level is nearly full."""
        return self.buckets * 2.0**self.levels

    def mergeable(self, other: Layout) -> bool:
        return self == other


@dataclass(frozen=True)
class LinearCounting(Layout):
    """One level: each item sets one of m bits."""

    levels: int = 1
    kind = "linear"

    def rho(self) -> list[float]:
        return [1.0 / self.buckets]

    def most(self) -> float:
        return self.buckets * (math.log(self.buckets) + 10)


@dataclass(frozen=True)
class Bloom(LinearCounting):
    """Each item sets up to k of m bits, so a bit gets a k-th of the budget."""

    k: int = 2
    kind = "bloom"

    @property
    def hashes(self) -> int:  # type: ignore[override]
        return self.k

    def rho(self) -> list[float]:
        return [1.0 - (1.0 - 1.0 / self.buckets) ** self.k]


@dataclass(frozen=True)
class Exponential(Layout):
    """m bits in a row whose probabilities fall off exponentially; grouped into levels of equal probability."""

    decay: float = 10.0
    kind = "exponential"

    def rho(self) -> list[float]:
        weights = [math.exp(-self.decay * (j + 0.5) / self.levels) for j in range(self.levels)]
        return [w / sum(weights) / self.buckets for w in weights]

    def most(self) -> float:
        return 10.0 / min(self.rho())
