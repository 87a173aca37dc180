"""Public hashes of items to cells, as column expressions.

`xxhash64` is the fast family; `md5` gives the same cells in other engines. Null items are not items,
so callers filter them; a null part of a composite item is a marker of its own.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..layout import Exponential, Layout

NULL_PART = "\\N"


def canonical(col: Column, dtype: str | None = None) -> Column:
    """The string form of an item or item part: integers as decimals, timestamps as micros, -0.0 as 0.0, arrays and maps as JSON."""
    if dtype in ("double", "float"):
        text = F.format_string("%.6f", F.when(col == 0, F.lit(0.0)).otherwise(col.cast("double")))
    elif dtype in ("timestamp", "timestamp_ntz"):
        text = F.unix_micros(col.cast("timestamp")).cast("string")
    elif dtype and dtype.startswith(("array", "map", "struct")):
        text = F.to_json(col)
    else:
        text = col.cast("string")
    return F.coalesce(text, F.lit(NULL_PART))


def joined(*parts: Column) -> Column:
    return parts[0].cast("string") if len(parts) == 1 else F.concat_ws("|", *[canonical(p) for p in parts])


def md5_60(text: Column) -> Column:
    """The first 60 bits of a string's MD5."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def level_of(bits: Column, levels: int) -> Column:
    """1 + number of trailing zeros, at most `levels`; bits must not be negative."""
    # x xor (x - 1) has the trailing zeros and the lowest one set; for 0 it is all ones
    return F.least(F.lit(levels), F.bit_count(bits.bitwiseXOR(bits - 1))).cast("int")


def cell_of(item: Column, layout: Layout, which: int = 0) -> Column:
    """The cell that an item sets; `which` numbers the hashes of layouts with several."""
    if layout.family == "md5":
        h = md5_60(F.concat_ws("|", F.lit(f"{layout.seed}:{which}"), item.cast("string")))
        bucket = F.pmod(h, F.lit(layout.buckets))
        rest = F.expr("0") if layout.levels == 1 else F.call_function("div", h, F.lit(layout.buckets))
    else:
        h = F.xxhash64(F.lit(f"bucket:{layout.seed}:{which}"), item)
        bucket = F.pmod(h, F.lit(layout.buckets))
        rest = F.xxhash64(F.lit(f"level:{layout.seed}:{which}"), item).bitwiseAND(F.lit((1 << 62) - 1))
    if layout.levels == 1:
        return bucket.cast("int")
    if isinstance(layout, Exponential):
        # inverse of the cumulative probabilities of the levels
        u, sums, total = F.pmod(rest, F.lit(1 << 40)) / float(1 << 40), [], 0.0
        for r in layout.rho()[:-1]:
            total += r * layout.buckets
            sums.append(total)
        level = F.aggregate(F.array(*[F.lit(x) for x in sums]), F.lit(1), lambda a, x: a + (u >= x).cast("int"))
    else:
        level = level_of(rest, layout.levels)
    return (bucket * layout.levels + level - 1).cast("int")


def bucket_level(cell: Column, layout: Layout) -> tuple[Column, Column]:
    return F.floor(cell / layout.levels).cast("int"), (F.pmod(cell, F.lit(layout.levels)) + 1).cast("int")
