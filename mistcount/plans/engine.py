"""Whole methods: from a table's items to private estimates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.budget import half_flip, symmetric
from ..layout import Layout
from ..operators.build import level_counts, sketch
from ..operators.estimate import cardinality, cardinality_symmetric
from ..operators.merge import checked_against, mergeable_groups, union_plain, union_randomized, union_xor
from ..operators.privatize import flip
from . import arrow


def count_private(
    df: DataFrame, item: Column, epsilon: float, layout: Layout, key: str, release: str, by: list[str] | None = None, method: str = "randomized", solver: str = "safe", noise: str = "stream",
) -> DataFrame:
    """(by, ones, n_hat, stderr, ...) of one private sketch a group. Bits are packed and flipped in place, so a group costs
    a few rows; `noise` is that of `arrow.flip_packed`. Layouts of several hashes an item take the long form."""
    mechanism = half_flip(epsilon) if method == "xor" else symmetric(epsilon)
    if layout.hashes > 1:
        levels = level_counts(flip(sketch(df, item, layout, by), mechanism, key, release, by), layout, by)
    else:
        levels = arrow.level_counts_packed(arrow.flip_packed(arrow.sketch_packed(df, item, layout, by), mechanism, layout, key, release, by, noise), layout, by or [])
    return cardinality(levels, layout, mechanism.p, mechanism.q, solver).withColumn("eps_effective", F.lit(float(epsilon)))


def union_of_released(noisy: DataFrame, layout: Layout, salt: str, sketches: DataFrame, by: list[str] | None = None, method: str = "randomized", solver: str = "safe") -> DataFrame:
    """Estimates of unions of released sketches (by, ..., cell, bit, eps). sketches: their catalogue rows (io.described),
    by group; an error is raised where they cannot be merged, or where a cell lacks some of them."""
    by = by or []
    if method == "randomized":
        levels = level_counts(union_randomized(noisy, salt, by), layout, by, ["eps_effective", "n_sources"])
    else:
        levels = level_counts(union_xor(noisy, by), layout, by, ["eps_effective", "n_sources"])
    levels = checked_against(levels, mergeable_groups(sketches, by), by)
    lacking = F.raise_error(F.lit("cells and catalogue hold different numbers of sketches")).cast("long")
    levels = levels.withColumn("n_sources", F.when(F.col("n_sources") == F.col("n_checked"), F.col("n_sources")).otherwise(lacking)).drop("n_checked")
    if method == "randomized":
        return cardinality_symmetric(levels, layout, solver=solver)
    return cardinality(levels, layout, F.lit(0.5), 0.5 * F.exp(-F.col("eps_effective")), solver)


def release_roll_up(plain: DataFrame, layout: Layout, epsilon: float, key: str, release: str, fine: list[str], coarse: list[str]) -> DataFrame:
    """Inside one trust boundary plain sketches are united first and flipped once; merging noise is for
    sketches that come from elsewhere."""
    united = union_plain(plain.drop(*[c for c in fine if c not in coarse]), coarse)
    mechanism = symmetric(epsilon)
    return flip(united, mechanism, key, release, coarse)
