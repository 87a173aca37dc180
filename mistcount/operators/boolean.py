"""Boolean operations on symmetric noisy bits."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.budget import combine_or, combine_xor, combine_xor_column
from .merge import merge_pair, union_randomized


def not_(cells: DataFrame) -> DataFrame:
    """Complements keep their budget: a symmetric flip doesn't tell ones from zeros."""
    return cells.withColumn("bit", 1 - F.col("bit"))


def xor_agg(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The XOR of noisy bits is the noisy XOR already."""
    return cells.groupBy(*(by or []), "cell").agg(F.pmod(F.sum("bit"), F.lit(2)).cast("int").alias("bit"), combine_xor_column(F.col("eps")).alias("eps_effective"))


def or_agg(cells: DataFrame, salt: str, by: list[str] | None = None) -> DataFrame:
    return union_randomized(cells, salt, by)


def and_agg(cells: DataFrame, salt: str, by: list[str] | None = None) -> DataFrame:
    return union_randomized(cells, salt, by, flipped=True)


def binary(a: DataFrame, b: DataFrame, e1: float, e2: float, truth: tuple[int, int, int, int], salt: str) -> tuple[DataFrame, float]:
    """Any of the 16 operations, given by its outputs for the bits 00, 01, 10, 11, and its budget.

    Constants need no data and have any budget. Operations of one operand keep that one's.
    """
    x, y = a.select("cell", "bit"), b.select("cell", "bit")
    if len(set(truth)) == 1:
        return x.withColumn("bit", F.lit(truth[0])), float("inf")
    for own, frame, eps in (((0, 0, 1, 1), x, e1), ((0, 1, 0, 1), y, e2)):
        if truth == own:
            return frame, eps
        if truth == tuple(1 - t for t in own):
            return not_(frame), eps
    odd = truth in ((0, 1, 1, 0), (1, 0, 0, 1))
    if odd:
        both = x.withColumnRenamed("bit", "x").join(y.withColumnRenamed("bit", "y"), "cell").select("cell", F.pmod(F.col("x") + F.col("y"), F.lit(2)).cast("int").alias("bit"))
        return (both if truth[0] == 0 else not_(both)), combine_xor([e1, e2])
    return merge_pair(x, y, e1, e2, salt, truth=truth), combine_or([e1, e2])


def debiased_count(cells: DataFrame, p: float, q: float, by: list[str] | None = None) -> DataFrame:
    """Unbiased number of true ones among noisy bits."""
    return cells.groupBy(*(by or [])).agg(((F.sum("bit") - q * F.count("*")) / (p - q)).alias("n_ones"), F.count("*").alias("n_bits"))
