"""Packed sketches in numpy, for groups or sketches too many for the long form."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.budget import Flip
from ..functions.noise import ONE
from ..functions.vectorised import fit
from ..layout import Layout
from ..operators.build import BITMAP, packed

#: First-level tasks for a group's sketches.
SALTS = 16


def _bits(raw: bytes) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little")


def all_bitmaps(bitmaps: DataFrame, groups: DataFrame, layout: Layout, by: list[str]) -> DataFrame:
    """(by, bucket_no, bits) with the bitmaps that have no ones: flips and merges act on every cell. groups: a row a sketch."""
    count = -(-layout.cells // BITMAP)
    spots = groups.select(*[F.col(c).alias(f"_{c}") for c in by], F.explode(F.sequence(F.lit(1).cast("long"), F.lit(count).cast("long"))).alias("_no"))
    same = F.col("bucket_no") == F.col("_no")
    for c in by:
        same &= F.col(c).eqNullSafe(F.col(f"_{c}"))
    return spots.join(bitmaps.select(*by, "bucket_no", "bits"), same, "left").select(*[F.col(f"_{c}").alias(c) for c in by], F.col("_no").alias("bucket_no"), F.coalesce("bits", F.lit(bytearray(BITMAP // 8))).alias("bits"))


def sketch_packed(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None) -> DataFrame:
    """Plain packed sketches with all their bitmaps, one for each group that occurs (also with null items only)."""
    by = by or []
    return all_bitmaps(packed(df, item, layout, by), df.select(*by).distinct() if by else df.sparkSession.range(1), layout, by)


#: Rows of bitmaps that a task holds at a time.
_ROWS = 256


def _draws(kind: str, place: str, first: int, count: int) -> np.ndarray:
    """Uniform 52-bit integers of the cells from `first` on."""
    if kind == "stream":
        return np.frombuffer(hashlib.shake_256(f"{place}|{first}".encode()).digest(8 * count), "<u8") >> np.uint64(12)
    start = hashlib.sha256(f"{place}|".encode())

    def one(cell: int) -> bytes:
        h = start.copy()
        h.update(b"%d" % cell)
        return h.digest()[:8]

    return np.frombuffer(b"".join(map(one, range(first, first + count))), ">u8") >> np.uint64(12)


def flip_packed(bitmaps: DataFrame, mechanism: Flip, layout: Layout, key: str, release: str, by: list[str] | None = None, noise: str = "stream") -> DataFrame:
    """Noisy copies of packed sketches, bitmap by bitmap: nothing is shuffled, and no row is made for a cell.

    Every sketch must have all its bitmaps. The noise is a function of key, release, group and cell, with either source:
    "stream" takes it from an extendable-output hash (SHAKE-256) of key, release, group and bitmap; "cell" hashes
    each cell, as the long form's flip() does, so that both forms (and SQL) give the same bits; it takes some 50 times longer.
    The key stands in the function that is shipped to the workers, not in the plan.
    """
    by = by or []
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in bitmaps.select(*by, "bucket_no").schema.fields)
    one, zero = np.uint64(int(mechanism.p * ONE)), np.uint64(int(mechanism.q * ONE))

    def flipped(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in rows:
            for at in range(0, whole.num_rows, _ROWS):
                batch, out = whole.slice(at, _ROWS), []
                for name, no, raw in zip(*(batch.column(c).to_pylist() for c in ("_name", "bucket_no", "bits")), strict=True):
                    first = (no - 1) * BITMAP
                    count = max(0, min(BITMAP, layout.cells - first))
                    place = "|".join(["flip", key, release, *([name] if by else [])])
                    bits = np.zeros(BITMAP, np.uint8)
                    bits[:count] = _draws(noise, place, first, count) < np.where(_bits(raw)[:count] == 1, one, zero)
                    out.append(np.packbits(bits, bitorder="little").tobytes())
                yield pa.record_batch([*[batch.column(c) for c in (*by, "bucket_no")], pa.array(out, pa.binary())], names=[*by, "bucket_no", "bits"])

    named = bitmaps.select(*by, "bucket_no", "bits", F.concat_ws("|", *[F.col(c).cast("string") for c in by]).alias("_name"))
    return named.mapInArrow(flipped, f"{kinds}, bits binary")


def _whole(log: float) -> int:
    """A logarithm in units of 2^-60: integers add up to the same in any order, so all bitmaps of a union get one budget."""
    return int(math.ldexp(max(log, -1e6), 60))


def merge_packed(bitmaps: DataFrame, layout: Layout, by: list[str], salt: str, noise: str = "stream") -> DataFrame:
    """(by, bucket_no, bits, eps_effective, n_sources): the randomized union of packed symmetric sketches (by, ..., bucket_no, bits, eps).

    Two levels: tasks first add up the ones and their budgets of some sketches, then these sums; so a group of
    any number of sketches needs no more than SALTS pairs of arrays in one task. Every sketch must have all its
    bitmaps (`all_bitmaps`), or an error is raised. Merge draws need independence, not secrecy; with noise "cell" they are
    those of merge.union_randomized.
    """
    keys = [*by, "bucket_no"]
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in bitmaps.select(*keys).schema.fields)

    def partial(key: tuple, rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ones, spent, log_missing, count = np.zeros(BITMAP, np.int32), np.zeros(BITMAP), 0, 0
        for batch in rows:
            for raw, eps in zip(batch.column("bits").to_pylist(), batch.column("eps").to_pylist(), strict=True):
                bit = _bits(raw)
                ones += bit
                spent[bit == 1] += eps
                log_missing += 0 if np.isinf(eps) else _whole(np.log(-np.expm1(-eps)))
                count += 1
        cells = [pa.array([k.as_py()], k.type) for k in key[:-1]]
        yield pa.record_batch([*cells, pa.array([ones.tobytes()], pa.binary()), pa.array([spent.tobytes()], pa.binary()), pa.array([str(log_missing)]), pa.array([count])], names=[*keys, "ones", "spent", "log_missing", "sketches"])

    def final(key: tuple, rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ones, spent, log_missing, sketches = np.zeros(BITMAP, np.int64), np.zeros(BITMAP), 0, 0
        for batch in rows:
            for a, b, c, n in zip(*(batch.column(x).to_pylist() for x in ("ones", "spent", "log_missing", "sketches")), strict=True):
                sketches += n
                ones += np.frombuffer(a, np.int32)
                spent += np.frombuffer(b, float)
                log_missing += int(c)
        left = -np.expm1(math.ldexp(log_missing, -60))  # exp of minus the effective budget
        chance = np.where(ones == 0, 0.0, (1 - np.where(ones % 2, -1.0, 1.0) * np.exp(-spent)) / (1 + left))
        first = (key[-1].as_py() - 1) * BITMAP
        count = max(0, min(BITMAP, layout.cells - first))
        drawn = np.zeros(BITMAP, bool)
        drawn[:count] = _draws(noise, "|".join(["merge", salt, *[str(k.as_py()) for k in key[:-1]]]), first, count) < np.floor(chance[:count] * ONE).astype(np.uint64)
        star = np.inf if left == 0 else -np.log(left)
        cells = [pa.array([k.as_py()], k.type) for k in key]
        yield pa.record_batch([*cells, pa.array([np.packbits(drawn, bitorder="little").tobytes()], pa.binary()), pa.array([float(star)]), pa.array([sketches])], names=[*keys, "bits", "eps_effective", "n_sources"])

    salted = bitmaps.select(*keys, "bits", F.col("eps").cast("double").alias("eps"), F.pmod(F.xxhash64("bits"), F.lit(SALTS)).alias("_salt"))
    sums = salted.groupBy(*keys, "_salt").applyInArrow(partial, f"{kinds}, ones binary, spent binary, log_missing string, sketches long")
    merged = sums.groupBy(*keys).applyInArrow(final, f"{kinds}, bits binary, eps_effective double, n_sources long")
    # a group's few bitmaps must all come from as many sketches
    group = Window.partitionBy(*(by or [F.lit(0)]))
    fine = (F.count("*").over(group) == -(-layout.cells // BITMAP)) & (F.min("n_sources").over(group) == F.max("n_sources").over(group))
    whole = F.when(fine, F.col("n_sources")).otherwise(F.raise_error(F.lit("a sketch lacks some of its bitmaps")).cast("long"))
    return merged.select(*keys, "bits", "eps_effective", whole.alias("n_sources")).where("n_sources > 0")


def level_counts_packed(bitmaps: DataFrame, layout: Layout, by: list[str]) -> DataFrame:
    """(by, ones) from packed sketches."""
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in bitmaps.select(*by).schema.fields)

    def count(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out = []
            for no, raw in zip(batch.column("bucket_no").to_pylist(), batch.column("bits").to_pylist(), strict=True):
                cells = np.flatnonzero(_bits(raw)) + (no - 1) * BITMAP
                out.append(np.bincount(cells[cells < layout.cells] % layout.levels, minlength=layout.levels).tolist())
            yield pa.record_batch([*[batch.column(c) for c in by], pa.array(out, pa.list_(pa.int64()))], names=[*by, "part"])

    parts = bitmaps.select(*by, "bucket_no", "bits").mapInArrow(count, f"{kinds}, part array<long>")
    sums = [F.sum(F.col("part")[j]).alias(f"_{j}") for j in range(layout.levels)]
    return parts.groupBy(*by).agg(*sums).select(*by, F.array(*[F.col(f"_{j}") for j in range(layout.levels)]).alias("ones"))


def fit_udf(layout: Layout, p: float, q: float, steps: int = 60):
    """The fit of level counts by halving, for batches of sketches at once."""

    @F.pandas_udf(T.DoubleType())
    def found(ones: pd.Series) -> pd.Series:
        return pd.Series(fit(np.stack(ones.to_numpy()), layout, p, q, steps) if len(ones) else [], dtype=float)

    return found


def cells_by_table_function(spark: SparkSession, bitmaps: DataFrame, layout: Layout) -> DataFrame:
    """g, bucket, level of the ones of packed sketches, by a Python table function."""
    levels, cells = layout.levels, layout.cells

    class SketchCells:
        def eval(self, bucket_no: int, bits: bytes):
            at = np.flatnonzero(np.unpackbits(np.frombuffer(bits, np.uint8), bitorder="little")) + (bucket_no - 1) * 32768
            for cell in at[at < cells].tolist():
                yield cell // levels, cell % levels + 1

    spark.udtf.register("sketch_cells", F.udtf(SketchCells, returnType="bucket int, level int"))
    bitmaps.createOrReplaceTempView("_sketch_bitmaps")
    return spark.sql("SELECT b.g, c.bucket, c.level FROM _sketch_bitmaps b, LATERAL sketch_cells(b.bucket_no, b.bits) c")
