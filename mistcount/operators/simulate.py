"""Sketches drawn from their law, without items: experiments with many trials need no scan.

Four laws: the exact one (items of a fixed number, hashed), the multinomial of the cells' counts (the same
law, drawn without items), independent cells with the right margins, and a Poisson number of items, under
which cells are independent too.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import draw, threshold
from ..layout import Layout


def _rho(layout: Layout, cell: Column) -> Column:
    return F.element_at(F.array(*[F.lit(r) for r in layout.rho()]), (F.pmod(cell, F.lit(layout.levels)) + 1).cast("int"))


def _grid(trials: DataFrame, layout: Layout) -> DataFrame:
    cells = trials.sparkSession.range(layout.cells).select(F.col("id").cast("int").alias("cell"))
    return cells.crossJoin(F.broadcast(trials))


def independent_cells(trials: DataFrame, layout: Layout, key: str, by: list[str]) -> DataFrame:
    """(by..., cell, bit) for trials with columns by and n: each cell is 1 with its own chance."""
    grid = _grid(trials, layout)
    full = -F.expm1(F.col("n") * F.log1p(-_rho(layout, F.col("cell"))))
    u = draw("sim", key, *[F.col(c) for c in by], F.col("cell"))
    return grid.withColumn("bit", (u < threshold(full)).cast("int"))


def poissonized(trials: DataFrame, layout: Layout, key: str, by: list[str]) -> DataFrame:
    """The same for a Poisson(n) number of items: a cell stays 0 with chance exp(-n rho)."""
    grid = _grid(trials, layout)
    full = -F.expm1(-F.col("n") * _rho(layout, F.col("cell")))
    u = draw("sim", key, *[F.col(c) for c in by], F.col("cell"))
    return grid.withColumn("bit", (u < threshold(full)).cast("int"))


def items(trials: DataFrame, n: int) -> DataFrame:
    """Trials with n distinct items each: item numbers, to be hashed with the trial in their seed."""
    return trials.sparkSession.range(n).select(F.col("id").alias("i")).crossJoin(F.broadcast(trials))


def exact(trials: DataFrame, n: int, layout: Layout, by: list[str]) -> DataFrame:
    """Dense sketches of n hashed items for each trial."""
    from .build import densify, set_cells

    rows = items(trials, n).withColumn("item", F.concat_ws("|", *[F.col(c).cast("string") for c in by], F.col("i").cast("string")))
    return densify(set_cells(rows, F.col("item"), layout, by), trials, layout, by)


def multinomial(trials: DataFrame, n: int, layout: Layout, key: str, by: list[str]) -> DataFrame:
    """Dense sketches of n items whose cells are drawn from keyed uniforms rather than hashed."""
    from .build import densify

    rows = items(trials, n)
    parts = [F.col(c) for c in by]
    bucket = F.pmod(draw("sim", key, "bucket", *parts, F.col("i")), F.lit(layout.buckets))
    bits = draw("sim", key, "level", *parts, F.col("i"))
    level = F.least(F.lit(layout.levels), F.bit_count(bits.bitwiseXOR(bits - 1)))
    cells = rows.select(*by, (bucket * layout.levels + level - 1).cast("int").alias("cell")).distinct()
    return densify(cells, trials, layout, by)


def flip_counts(cells: DataFrame, p: float, q: float, key: str, by: list[str]) -> DataFrame:
    """Flips the bits of simulated sketches; by names a sketch."""
    u = draw("flip", key, *[F.col(c) for c in by], F.col("cell"))
    return cells.withColumn("bit", F.when(F.col("bit") == 1, (u < threshold(p)).cast("int")).otherwise((u < threshold(q)).cast("int")))


def private_levels(trials: DataFrame, layout: Layout, key: str, by: list[str]) -> DataFrame:
    """(by, n, p, q, ones) of noisy independent-cell sketches in one draw a cell: bit and flip together
    give a 1 with chance q + (p - q)(1 - g^n). trials has by, n, p, q."""
    grid = _grid(trials, layout)
    full = -F.expm1(F.col("n") * F.log1p(-_rho(layout, F.col("cell"))))
    u = draw("sim", key, *[F.col(c) for c in by], F.col("cell"))
    noisy = grid.withColumn("bit", (u < threshold(F.col("q") + (F.col("p") - F.col("q")) * full)).cast("int"))
    from .build import level_counts

    return level_counts(noisy, layout, by, ["n", "p", "q"])
