"""Plain sketches: from items to cells, in the long, packed and count forms.

The long form has a row a cell (group columns, cell, bit) and is what flips and merges are defined on.
The packed form keeps Spark's bitmaps, 32,768 cells a row. The count form has one array a sketch.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import cell_of
from ..layout import Layout

BITMAP = 32768


def set_cells(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None) -> DataFrame:
    """Distinct (by, cell) that the items set. Repetition and order don't matter; null items are skipped.

    The distinct is on cells, not items: a task hands on at most a group's cells, however many items.
    """
    by = by or []
    rows = df.where(item.isNotNull())
    if layout.hashes > 1:
        cell = F.explode(F.array(*[cell_of(item, layout, i) for i in range(layout.hashes)]))
    else:
        cell = cell_of(item, layout)
    return rows.select(*by, cell.alias("cell")).distinct()


def cell_frame(df: DataFrame, layout: Layout) -> DataFrame:
    """All cells of the layout, in parallel."""
    return df.sparkSession.range(layout.cells).select(F.col("id").cast("int").alias("cell"))


def densify(cells: DataFrame, groups: DataFrame, layout: Layout, by: list[str]) -> DataFrame:
    """(by, cell, bit) with the zeros: flips act on every cell, so a cell that is missing would tell the truth.

    groups has one row a sketch, so the product has as many rows as the sketches have cells.
    """
    grid = cell_frame(cells, layout).crossJoin(groups.select(*by)) if by else cell_frame(cells, layout)
    return grid.join(cells.withColumn("one", F.lit(1)), [*by, "cell"], "left").select(*by, "cell", F.coalesce("one", F.lit(0)).alias("bit"))


def sketch(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None) -> DataFrame:
    """Dense plain sketches, one for each group that occurs (also with null items only)."""
    by = by or []
    return densify(set_cells(df, item, layout, by), df.select(*by).distinct() if by else df, layout, by)


def packed(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None) -> DataFrame:
    """(by, bucket_no, bits): cells numbered from 1, so that a default sketch fills three bitmaps exactly."""
    by = by or []
    at = cell_of(item, layout).cast("long") + 1
    return df.where(item.isNotNull()).groupBy(*by, F.bitmap_bucket_number(at).alias("bucket_no")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))


def unpack(bitmaps: DataFrame, layout: Layout, by: list[str]) -> DataFrame:
    """The long form of packed sketches, zeros included; bits stand little-endian in a byte."""
    spots = bitmaps.select(*by, "bucket_no", "bits", F.explode(F.sequence(F.lit(0), F.lit(BITMAP - 1))).alias("pos"))
    byte = F.conv(F.hex(F.substring("bits", F.floor(F.col("pos") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    cell = ((F.col("bucket_no") - 1) * BITMAP + F.col("pos")).cast("int")
    return spots.select(*by, cell.alias("cell"), F.getbit(byte, F.pmod("pos", F.lit(8))).cast("int").alias("bit")).where(F.col("cell") < layout.cells)


def level_counts(cells: DataFrame, layout: Layout, by: list[str] | None = None, extra: list[str] | None = None) -> DataFrame:
    """(by, extra, ones): the number of ones of each level, all that a fit needs. extra: columns that a group determines."""
    by, extra = by or [], extra or []
    level = F.pmod("cell", F.lit(layout.levels))
    sums = cells.groupBy(*by, *extra, level.alias("_level")).agg(F.sum("bit").alias("_k"))
    found = sums.groupBy(*by, *extra).agg(F.map_from_entries(F.collect_list(F.struct("_level", "_k"))).alias("m"))
    levels = F.transform(F.sequence(F.lit(0), F.lit(layout.levels - 1)), lambda j: F.coalesce(F.element_at("m", j), F.lit(0)).cast("long"))
    return found.select(*by, *extra, levels.alias("ones"))
