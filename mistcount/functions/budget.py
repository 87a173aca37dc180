"""Flip mechanisms, their budgets, and how budgets combine when sketches are merged."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Flip:
    """A 1 stays 1 with probability p; a 0 becomes 1 with probability q."""

    p: float
    q: float
    kind: str = "custom"  # symmetric and half flips can be merged

    @property
    def epsilon(self) -> float:
        return epsilon_of(self.p, self.q)


def epsilon_of(p: float, q: float) -> float:
    """The least budget that a flip meets, for q <= 1/2 <= p."""
    if not (q <= 0.5 <= p):
        raise ValueError("q must be at most and p at least one half")
    if not (0 < p < 1 and 0 < q < 1):
        return math.inf
    return math.log(max(p / q, (1 - q) / (1 - p)))


def is_private(p: float, q: float, epsilon: float) -> bool:
    return 0 < p < 1 and 0 < q < 1 and max(p / q, (1 - q) / (1 - p)) <= math.exp(epsilon) * (1 + 1e-12)


def epsilon_column(p: Column, q: Column) -> Column:
    safe = (p < 1) & (q > 0)
    return F.when(safe, F.log(F.greatest(p / F.when(safe, q), (1 - q) / F.when(safe, 1 - p)))).otherwise(F.lit(float("inf")))


def symmetric(epsilon: float) -> Flip:
    """Each bit is told right with odds e^epsilon; an infinite budget is the non-private sketch."""
    q = 0.0 if math.isinf(epsilon) else 1 / (math.exp(epsilon) + 1)
    return Flip(1 - q, q, "symmetric")


def half_flip(epsilon: float) -> Flip:
    """Ones become fair coins: the only kind that a deterministic merge allows, here at its least noise."""
    return Flip(0.5, 0.5 * math.exp(-epsilon), "half")


def half_flip_loose(epsilon: float) -> Flip:
    """The earlier method's choice of q for the same budget."""
    return Flip(0.5, 1 / (2 + epsilon), "half")


def half_flip_appendix(epsilon: float) -> Flip:
    """The earlier method's other choice of q."""
    return Flip(0.5, 1 / (math.exp(epsilon) + 1), "half")


def equivalent_half(flip: Flip) -> float:
    """The budget at which half_flip draws as this half flip does."""
    return -math.log(2 * flip.q)


def loose_equivalent(epsilon: float) -> float:
    """The budget at which the loose choice is as noisy as the tight one at epsilon."""
    return 2 * math.expm1(epsilon)


#: For epsilon below this, 1 - w_i products leave nothing to tell.
TINY = 1e-9


def combine_or(epsilons: list[float]) -> float:
    """Effective budget of a union of sketches; the same for intersections, and for half flips."""
    missing = math.prod(-math.expm1(-e) for e in epsilons)
    return math.inf if missing == 1 else -math.log1p(-missing)


def combine_xor(epsilons: list[float]) -> float:
    product = math.prod(math.tanh(e / 2) for e in epsilons)
    return math.inf if product == 1 else 2 * math.atanh(product)


def _exact_sum(x: Column) -> Column:
    """Sum in decimals, which no order of the rows changes: the budgets of a group's cells must be equal to the last bit."""
    return F.sum(x.cast("decimal(38,18)")).cast("double")


def combine_or_column(epsilon: Column) -> Column:
    """Aggregate of combine_or over rows: sums of logs, with infinite budgets leaving the sum as it is."""
    logs = F.when(epsilon == float("inf"), 0.0).otherwise(F.log(-F.expm1(-epsilon)))
    missing = F.exp(_exact_sum(logs))
    return F.when(missing == 1, F.lit(float("inf"))).otherwise(-F.log1p(-missing))


def combine_xor_column(epsilon: Column) -> Column:
    logs = F.when(epsilon == float("inf"), 0.0).otherwise(F.log(F.tanh(epsilon / 2)))
    t = F.exp(_exact_sum(logs))
    return F.when(t == 1, F.lit(float("inf"))).otherwise(F.log((1 + t) / F.when(t < 1, 1 - t)))


def symmetric_q(epsilon: Column) -> Column:
    return F.when(epsilon == float("inf"), 0.0).otherwise(1 / (F.exp(epsilon) + 1))


def transition(e1: float, e2: float, target: str = "or", truth: tuple[int, int, int, int] | None = None) -> list[float]:
    """Chances of a 1 for the noisy pairs 00, 01, 10, 11, from the inverse of the two flips' Kronecker product.

    `truth` gives the outputs of any operation for these pairs of true bits.
    """
    import numpy as np

    truth = truth or {"or": (0, 1, 1, 1), "and": (0, 0, 0, 1), "xor": (0, 1, 1, 0)}[target]
    star = combine_xor([e1, e2]) if truth in ((0, 1, 1, 0), (1, 0, 0, 1)) else combine_or([e1, e2])
    q = [symmetric(e).q for e in (e1, e2, star)]
    flips = [np.array([[1 - x, x], [x, 1 - x]]) for x in q[:2]]
    wanted = np.array([1 - q[2] if t else q[2] for t in truth])
    return np.linalg.solve(np.kron(*flips), wanted).tolist()
