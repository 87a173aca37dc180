"""From level counts to estimates, and planning from the error formula."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import likelihood as lk
from ..functions.budget import combine_or, half_flip, symmetric, symmetric_q
from ..layout import Layout

Z95 = 1.959963984540054


def cardinality(levels: DataFrame, layout: Layout, p: Column | float, q: Column | float, solver: str = "safe", method: str = "likelihood", z: float = Z95) -> DataFrame:
    """levels with n_hat, stderr, rel_stderr, ci_low, ci_high and status."""
    n_hat, status = lk.estimate(F.col("ones"), layout, p, q, solver, poisson=method == "poisson")
    fitted = levels.withColumn("n_hat", n_hat).withColumn("status", status)
    fitted = fitted.withColumn("stderr", lk.stderr(layout, F.col("n_hat"), p, q))
    width = z * F.col("stderr")
    return fitted.withColumns({"rel_stderr": F.try_divide("stderr", "n_hat"), "ci_low": F.greatest(F.lit(0.0), F.col("n_hat") - width), "ci_high": F.col("n_hat") + width})


def cardinality_symmetric(levels: DataFrame, layout: Layout, eps: str = "eps_effective", solver: str = "safe") -> DataFrame:
    """The same for symmetric sketches whose effective budget is a column: merged ones are fitted like any other."""
    q = symmetric_q(F.col(eps))
    return cardinality(levels, layout, 1 - q, q, solver)


def asymptotic_constant(layout: Layout, p: float, q: float) -> float:
    """c with relative error c / sqrt(buckets) for large cardinalities."""
    n = layout.buckets * 2.0 ** (layout.levels // 2)
    return lk.stderr_value(layout, n, p, q) / n * math.sqrt(layout.buckets)


def stderr_after_merge(layout: Layout, epsilons: list[float], n: float, xor: bool = False) -> float:
    flip = (half_flip if xor else symmetric)(combine_or(epsilons))
    return lk.stderr_value(layout, n, flip.p, flip.q)


def plan_buckets(target: float, epsilon: float, n: float, levels: int = 24, most: int = 1 << 22) -> int:
    """The least power of two of buckets whose relative standard error at n is at most target."""
    flip, b = symmetric(epsilon), 16
    while b <= most:
        if lk.stderr_value(Layout(b, levels), n, flip.p, flip.q) / n <= target:
            return b
        b *= 2
    raise ValueError(f"no sketch of {most} buckets or fewer reaches {target} at a budget of {epsilon}")


def plan_epsilon(target: float, k: int, n: float, layout: Layout | None = None, most: float = 20.0) -> float:
    """The least budget, to 1e-6, at which the union of k sketches has relative error target at most."""
    layout = layout or Layout()
    error = lambda e: stderr_after_merge(layout, [e] * k, n) / n
    if error(most) > target:
        raise ValueError(f"a union of {k} sketches does not reach {target} at any budget up to {most}")
    low, high = 0.0, most
    while high - low > 1e-6:
        mid = (low + high) / 2
        low, high = (low, mid) if error(mid) <= target else (mid, high)
    return high


def plan_layout(n: float, epsilon: float, sizes: tuple[int, ...] = (64, 256, 1024, 4096), levels: int = 24) -> Layout:
    """Of these sizes the one of least error at n: small groups do better with fewer buckets."""
    flip = symmetric(epsilon)
    return min((Layout(b, levels) for b in sizes), key=lambda x: lk.stderr_value(x, n, flip.p, flip.q))
