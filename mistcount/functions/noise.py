"""Keyed draws: the noise of a release is a function of a secret key, the release and the cell.

A retried or recomputed task thus draws the same noise, where rand() would draw anew and let two noisy
copies of the same bits leave the process. The release must change whenever the data do. The purpose
keeps the draws of the stages (flip, merge, coin, simulation) apart. Anyone with the key can undo the
noise: the keys of tests and examples are public, and what they protect is not private.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52
ONE = 1 << BITS


def draw(purpose: str, key: str, *parts: Column | str | int) -> Column:
    """A uniform integer in [0, 2^52)."""
    texts = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    digest = F.sha2(F.concat_ws("|", F.lit(purpose), F.lit(key), *texts).cast("binary"), 256)
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long")


def threshold(p: Column | float) -> Column:
    """draw < threshold(p) with probability p, to 52 bits."""
    return F.lit(int(p * ONE)) if isinstance(p, int | float) else F.floor(p * float(ONE)).cast("long")


def bernoulli(u: Column, p: Column | float) -> Column:
    return (u < threshold(p)).cast("int")


def uniform(u: Column) -> Column:
    return u / float(ONE)
