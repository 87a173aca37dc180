"""Unions of sketches: plain, by XOR for half flips, and randomized for symmetric flips.

The randomized union of any number of sketches is one aggregation. For noisy bits a_i of budgets e_i,
the merged bit is 1 with chance r (1 - product of -exp(-e_i) over the ones), r = 1 / (1 + E), E = exp(-e*):
the number of ones and the sum of their budgets are all that a cell needs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.budget import combine_or_column, transition
from ..functions.noise import bernoulli, draw


def union_plain(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    return cells.groupBy(*(by or []), "cell").agg(F.max("bit").alias("bit"))


def union_packed(bitmaps: DataFrame, by: list[str] | None = None) -> DataFrame:
    return bitmaps.groupBy(*(by or []), "bucket_no").agg(F.bitmap_or_agg("bits").alias("bits"))


def union_xor(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Half-flipped sketches, each with its eps: XOR of the bits; budgets combine as in every union."""
    return cells.groupBy(*(by or []), "cell").agg(F.pmod(F.sum("bit"), F.lit(2)).cast("int").alias("bit"), combine_or_column(F.col("eps")).alias("eps_effective"), F.count("*").alias("n_sources"))


def merge_chance(ones: Column, spent: Column, eps_effective: Column) -> Column:
    """Chance of a 1 in the union, from the number of ones, the sum of their budgets, and the combined budget."""
    r = 1 / (1 + F.when(eps_effective == float("inf"), 0.0).otherwise(F.exp(-eps_effective)))
    sign = F.when(F.pmod(ones, F.lit(2)) == 0, 1.0).otherwise(-1.0)
    vanishing = F.when(spent == float("inf"), 0.0).otherwise(F.exp(-spent))
    return F.when(ones == 0, F.lit(0.0)).otherwise(r * (1 - sign * vanishing))


def effective(sketches: DataFrame, by: list[str]) -> DataFrame:
    """Combined budget of each group; sketches has a row a sketch."""
    return sketches.groupBy(*by).agg(combine_or_column(F.col("eps")).alias("eps_effective"), F.count("*").alias("n_sources"))


def union_randomized(cells: DataFrame, salt: str, by: list[str] | None = None, flipped: bool = False) -> DataFrame:
    """(by, cell, bit, eps_effective, n_sources) of symmetric sketches given as (by, ..., cell, bit, eps).

    With `flipped`, the intersection: the union's law on the complements. One shuffle, on (by, cell);
    tasks add up the sketches they hold first. A single sketch comes back as it is.
    """
    by = by or []
    bit = 1 - F.col("bit") if flipped else F.col("bit")
    sums = cells.groupBy(*by, "cell").agg(
        F.sum(bit).alias("m"), F.sum(F.when(bit == 1, F.col("eps")).otherwise(0.0)).alias("s"),
        # every sketch has a row in every cell, so a cell's rows give the group's budget as well
        combine_or_column(F.col("eps")).alias("eps_effective"), F.count("*").alias("n_sources"),
    )
    u = draw("merge", salt, *[F.col(c) for c in by], F.col("cell"))
    merged = bernoulli(u, merge_chance(F.col("m"), F.col("s"), F.col("eps_effective")))
    return sums.select(*by, "cell", (1 - merged if flipped else merged).alias("bit"), "eps_effective", "n_sources")


def merge_pair(a: DataFrame, b: DataFrame, e1: float, e2: float, salt: str, target: str = "or", truth=None) -> DataFrame:
    """Any operation on two noisy sketches (cell, bit), by the four chances of its transition."""
    t = transition(e1, e2, target, truth)
    pair = a.select("cell", F.col("bit").alias("x")).join(b.select("cell", F.col("bit").alias("y")), "cell")
    chance = F.element_at(F.array(*[F.lit(min(1.0, max(0.0, v))) for v in t]), (2 * F.col("x") + F.col("y") + 1).cast("int"))
    return pair.select("cell", bernoulli(draw("merge", salt, F.col("cell")), chance).alias("bit"))


def mergeable_groups(sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by, n_checked): the number of sketches of each group, or an error while it is read unless all have one layout
    and mechanism, each occurs once, and none has an ancestor in common with another, as merging shared noise breaks the
    merge's law. sketches: a row a sketch with by, sketch_id, layout, mechanism, lineage."""
    by = by or []
    rows = sketches.withColumn("_a", F.explode_outer("lineage"))
    # a row an ancestor: a sketch's own facts repeat, so its number of rows is counted by its ancestors' places
    own = sketches.groupBy(*by).agg(F.count_distinct("layout").alias("layouts"), F.count_distinct("mechanism.kind").alias("kinds"), F.count("*").alias("n"), F.count_distinct("sketch_id").alias("ids"))
    shared = rows.groupBy(*[F.col(c).alias(f"_{c}") for c in by]).agg(F.count("_a").alias("na"), F.count_distinct("_a").alias("da"))
    same = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in by]
    both = own.join(shared, same) if by else own.crossJoin(shared)
    verdict = (
        F.when(F.col("layouts") > 1, F.lit("layouts differ")).when(F.col("kinds") > 1, F.lit("mechanisms differ"))
        .when(F.col("ids") < F.col("n"), F.lit("a sketch occurs twice")).when(F.col("da") < F.col("na"), F.lit("sketches have an ancestor in common"))
    )
    return both.select(*by, F.when(verdict.isNotNull(), F.raise_error(verdict).cast("long")).otherwise(F.col("n")).alias("n_checked"))


def check_mergeable(sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The catalogue rows, or an error while they are read; each group by itself."""
    return checked_against(sketches, mergeable_groups(sketches, by), by).where("n_checked > 0").drop("n_checked")


def checked_against(rows: DataFrame, groups: DataFrame, by: list[str] | None = None) -> DataFrame:
    """rows with the n_checked of their group."""
    if not by:
        return rows.crossJoin(F.broadcast(groups))  # a single row
    named = groups.select(*[F.col(c).alias(f"_{c}") for c in by], "n_checked")
    return rows.join(named, [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in by]).drop(*[f"_{c}" for c in by])
