"""Flipping the bits of dense sketches, and what one item may touch."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.budget import Flip
from ..functions.hashing import md5_60
from ..functions.noise import bernoulli, draw


def flip(cells: DataFrame, mechanism: Flip, key: str, release: str, by: list[str] | None = None) -> DataFrame:
    """Noisy copies of the bits; the same key and release give the same noise."""
    u = draw("flip", key, release, *[F.col(c) for c in by or []], F.col("cell"))
    return cells.withColumn("bit", F.when(F.col("bit") == 1, bernoulli(u, mechanism.p)).otherwise(bernoulli(u, mechanism.q)))


def flip_symmetric(cells: DataFrame, epsilon: Column, key: str, release: str, by: list[str]) -> DataFrame:
    """Symmetric flips whose budget may differ from sketch to sketch; adds eps."""
    from ..functions.budget import symmetric_q

    u = draw("flip", key, release, *[F.col(c) for c in by], F.col("cell"))
    q = symmetric_q(epsilon)
    noisy = F.when(F.col("bit") == 1, bernoulli(u, 1 - q)).otherwise(bernoulli(u, q))
    return cells.withColumn("eps", epsilon).withColumn("bit", noisy)


def bound_groups(df: DataFrame, item: str, group: str, most: int) -> DataFrame:
    """Rows of at most `most` groups for each item, chosen by hash: an item's budget adds up over the groups
    that it is in, so bounding them bounds the whole."""
    pairs = df.select(item, group).distinct()
    ranked = pairs.withColumn("r", F.row_number().over(Window.partitionBy(item).orderBy(md5_60(F.concat_ws("|", F.col(item).cast("string"), F.col(group).cast("string"))), group)))
    return df.join(ranked.where(F.col("r") <= most).drop("r"), [item, group], "left_semi")
