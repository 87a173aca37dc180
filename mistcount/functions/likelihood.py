"""The composite likelihood of level counts, its derivatives, its maximum, and standard errors.

All are column expressions over an array of level counts: a sketch's fit is a projection, whatever the
number of sketches. With g_j the chance that an item misses a given cell of level j, a bit there is 1
with chance p - (p - q) g_j^n.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..layout import Layout

STEPS = 60
GRID = 128


def _num(x: Column | float) -> Column:
    return F.lit(float(x)) if isinstance(x, int | float) else x


def _rho(layout: Layout) -> Column:
    return F.array(*[F.lit(r) for r in layout.rho()])


def _total(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0.0), lambda a, x: a + x)


def _safe(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(a, b), F.lit(0.0))


def _parts(ones: Column, layout: Layout, n: Column, p: Column, q: Column, term, poisson: bool = False) -> Column:
    """Sum over levels of term(k, zeros, log g, g^n, chance of 0, chance of 1)."""

    def of(k: Column, r: Column) -> Column:
        lg = -r if poisson else F.log1p(-r)
        miss = F.exp(n * lg)
        # 1 - miss by expm1, so that small chances keep their digits
        one = q + (p - q) * -F.expm1(n * lg)
        return term(k.cast("double"), F.lit(float(layout.buckets)) - k, lg, miss, 1 - p + (p - q) * miss, one)

    return _total(F.zip_with(ones, _rho(layout), of))


def loglik(ones: Column, layout: Layout, n, p, q, poisson: bool = False) -> Column:
    log = lambda c, x: F.when(c == 0, 0.0).otherwise(c * F.log(F.greatest(x, F.lit(1e-300))))
    return _parts(ones, layout, _num(n), _num(p), _num(q), lambda k, z, lg, g, zero, one: log(z, zero) + log(k, one), poisson)


def score(ones: Column, layout: Layout, n, p, q, poisson: bool = False) -> Column:
    """First derivative in n."""
    p, q = _num(p), _num(q)

    def term(k, z, lg, g, zero, one):
        # without noise on ones the ratio tends to 1 where g^n vanishes
        ratio = F.when(p == 1, F.lit(1.0)).otherwise(_safe((p - q) * g, zero))
        return z * ratio * lg - k * _safe((p - q) * g, one) * lg

    return _parts(ones, layout, _num(n), p, q, term, poisson)


def hessian(ones: Column, layout: Layout, n, p, q) -> Column:
    """Second derivative in n."""
    p, q = _num(p), _num(q)

    def term(k, z, lg, g, zero, one):
        zeros = F.when(p == 1, F.lit(0.0)).otherwise(_safe((1 - p) * (p - q) * g, zero * zero))
        return lg * lg * (z * zeros - k * _safe(p * (p - q) * g, one * one))

    return _parts(ones, layout, _num(n), p, q, term)


def bisect(ones: Column, layout: Layout, p, q, low=0.0, high=None, steps: int = STEPS, poisson: bool = False) -> Column:
    """log n where the score changes its sign, between low and high, in a fixed number of halvings."""
    start = F.struct(_num(low).alias("a"), _num(25.0 if high is None else high).alias("b"))

    def halve(s: Column, _: Column) -> Column:
        mid = (s["a"] + s["b"]) / 2
        rises = score(ones, layout, F.exp(mid), p, q, poisson) > 0
        return F.struct(F.when(rises, mid).otherwise(s["a"]).alias("a"), F.when(rises, s["b"]).otherwise(mid).alias("b"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, halve, lambda s: (s["a"] + s["b"]) / 2)


def grid_then_bisect(ones: Column, layout: Layout, p, q, poisson: bool = False) -> Column:
    """As bisect, between the neighbours of the best of GRID log-spaced places: also right where a noisy likelihood has several humps."""
    top = math.log(layout.most())
    at = lambda i: i * (top / GRID)
    values = F.transform(F.sequence(F.lit(0), F.lit(GRID)), lambda i: F.struct(loglik(ones, layout, F.exp(at(i)), p, q, poisson).alias("l"), (-i).alias("i")))
    best = -F.array_max(values)["i"]
    return bisect(ones, layout, p, q, at(F.greatest(best - 1, F.lit(0))), at(F.least(best + 1, F.lit(GRID))), poisson=poisson)


def newton(ones: Column, layout: Layout, p, q, start: Column, steps: int = 40) -> Column:
    """Newton's steps in n from a start, each kept within a factor of two of the last place."""

    def step(n: Column, _: Column) -> Column:
        moved = n - _safe(score(ones, layout, n, p, q), hessian(ones, layout, n, p, q))
        return F.least(n * 2, F.greatest(n / 2, moved))

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start.cast("double"), step)


def estimate(ones: Column, layout: Layout, p, q, solver: str = "safe", poisson: bool = False) -> tuple[Column, Column]:
    """Cardinality and status (ok, zero, saturated, no_information) of level counts."""
    p, q = _num(p), _num(q)
    top = math.log(layout.most())
    if solver == "safe":
        found = F.exp(grid_then_bisect(ones, layout, p, q, poisson))
    elif solver == "bisect":
        found = F.exp(bisect(ones, layout, p, q, 0.0, 25.0 if layout.kind == "pcsa" else top, poisson=poisson))
    elif solver == "newton":
        found = newton(ones, layout, p, q, F.exp(bisect(ones, layout, p, q, 0.0, min(25.0, top), steps=12)))
    else:
        raise ValueError(solver)
    blank = (p - q) < 1e-9
    zero = score(ones, layout, F.lit(1.0), p, q, poisson) <= 0
    # with the largest cardinality still too small, the sketch is full
    full = score(ones, layout, F.lit(layout.most()), p, q, poisson) > 0
    status = F.when(blank, "no_information").when(zero, "zero").when(full, "saturated").otherwise("ok")
    return F.when(status == "ok", found).when(status == "zero", F.lit(0.0)), status


def stderr(layout: Layout, n, p, q) -> Column:
    """Standard error from the expected curvature at n."""
    n, p, q = _num(n), _num(p), _num(q)

    def of(r: Column) -> Column:
        lg = F.log1p(-r)
        g = F.exp(n * lg)
        zeros = F.when(p == 1, F.lit(0.0)).otherwise(_safe(1 - p, 1 - p + (p - q) * g))
        return lg * lg * g * (_safe(p, q + (p - q) * -F.expm1(n * lg)) - zeros)

    info = F.lit(float(layout.buckets)) * (p - q) * _total(F.transform(_rho(layout), of))
    return F.when((n > 0) & (info > 0), 1 / F.sqrt(F.when(info > 0, info)))


def observed_stderr(ones: Column, layout: Layout, n, p, q) -> Column:
    """Standard error from the curvature of the counts at hand."""
    h = -hessian(ones, layout, n, p, q)
    return F.when(h > 0, 1 / F.sqrt(F.when(h > 0, h)))


def sandwich_stderr(layout: Layout, n, p, q) -> Column:
    """Sensitivity and score variance together: sqrt(V) / S, with V under the cells' true dependence.

    Cells compete for items: two cells of chances r and s are both missed with chance (1 - r - s)^n, so
    their bits covary by (p - q)^2 ((1 - r - s)^n - g_r^n g_s^n).
    """
    n, p, q = _num(n), _num(p), _num(q)
    b = float(layout.buckets)

    def weight(r: Column) -> tuple[Column, Column, Column]:
        lg = F.log1p(-r)
        g = F.exp(n * lg)
        one = q + (p - q) * -F.expm1(n * lg)
        zero = F.greatest(1 - p + (p - q) * g, F.lit(1e-300))
        # d score / d bit, and the bit's own chance of a 1
        return -(p - q) * g * lg * (_safe(F.lit(1.0), one) + 1 / zero), one, g

    def own(r: Column) -> Column:
        w, one, _ = weight(r)
        return w * w * one * (1 - one) * b

    def pair(r: Column, i: Column, s: Column, j: Column) -> Column:
        (w, _, g), (v, _, h) = weight(r), weight(s)
        both = F.exp(n * F.log1p(-r - s)) - g * h
        count = b * b - F.when(i == j, b).otherwise(0.0)
        return w * v * (p - q) * (p - q) * both * count

    variance = _total(F.transform(_rho(layout), own)) + _total(F.transform(_rho(layout), lambda r, i: _total(F.transform(_rho(layout), lambda s, j: pair(r, i, s, j)))))
    return stderr(layout, n, p, q) ** 2 * F.sqrt(F.greatest(variance, F.lit(0.0)))


# The same formulas as plain numbers, for planning.


def stderr_value(layout: Layout, n: float, p: float, q: float) -> float:
    info = 0.0
    for r in layout.rho():
        lg = math.log1p(-r)
        g = math.exp(n * lg)
        one, zero = q + (p - q) * -math.expm1(n * lg), 1 - p + (p - q) * g
        info += lg * lg * g * ((p / one if one else 0.0) - ((1 - p) / zero if p < 1 else 0.0))
    info *= layout.buckets * (p - q)
    return 1 / math.sqrt(info) if info > 0 else math.inf
