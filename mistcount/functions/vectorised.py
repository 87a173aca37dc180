"""The fit and the interval estimator for many sketches at once, on numpy arrays: what the expressions give, faster."""

from __future__ import annotations

import math

import numpy as np

from ..layout import Layout


def fit(ones: np.ndarray, layout: Layout, p: np.ndarray | float, q: np.ndarray | float, steps: int = 60) -> np.ndarray:
    """Cardinalities of level counts (a row a sketch) by halving log n: 0 if no items are likelier, nan if a sketch is
    full or its bits tell nothing."""
    k, lg = np.asarray(ones, float), np.log1p(-np.array(layout.rho()))
    p, q = (np.broadcast_to(np.asarray(x, float), len(k))[:, None] for x in (p, q))

    def rises(n: np.ndarray) -> np.ndarray:
        g = np.exp(n[:, None] * lg)
        with np.errstate(invalid="ignore", divide="ignore"):
            zero = np.where(p == 1, 1.0, np.nan_to_num((p - q) * g / (1 - p + (p - q) * g)))
            one = np.nan_to_num((p - q) * g / (p - (p - q) * g))
        return ((layout.buckets - k) * zero * lg - k * one * lg).sum(axis=1) > 0

    most = layout.most()
    a, b = np.zeros(len(k)), np.full(len(k), 25.0 if layout.kind == "pcsa" else math.log(most))
    for _ in range(steps):
        mid = (a + b) / 2
        up = rises(np.exp(mid))
        a, b = np.where(up, mid, a), np.where(up, b, mid)
    found = np.where(rises(np.ones(len(k))), np.exp((a + b) / 2), 0.0)
    nothing = (p - q)[:, 0] < 1e-9
    return np.where(nothing | rises(np.full(len(k), float(most))), np.nan, found)


def interval(ones: np.ndarray, layout: Layout, p: np.ndarray | float, q: np.ndarray | float, betas: np.ndarray) -> np.ndarray:
    """The midpoint of the levels' intersection at the first of the tolerances at which it is neither empty nor
    unbounded; nan if there is none."""
    k, lg = np.asarray(ones, float), np.log1p(-np.array(layout.rho()))
    p, q = (np.broadcast_to(np.asarray(x, float), len(k))[:, None] for x in (p, q))
    share, out = (p - k / layout.buckets) / (p - q), np.full(len(k), np.nan)
    for beta in betas:
        left = np.flatnonzero(np.isnan(out))
        if not len(left):
            break
        low, high = share[left] + beta, share[left] - beta
        a = np.where(low <= 0, np.inf, np.log(np.clip(low, 1e-300, 1.0)) / lg).max(axis=1)
        b = np.where(high >= 1, 0.0, np.where(high <= 0, np.inf, np.log(np.maximum(high, 1e-300)) / lg)).min(axis=1)
        fits = (a <= b) & np.isfinite(a) & np.isfinite(b)
        out[left[fits]] = (a[fits] + b[fits]) / 2
    return out
