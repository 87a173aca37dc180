"""Shared plumbing of the corpus operators: the shared folder, written tables and Arrow helpers."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: ASCII white space, which separates words: tab, line feed, vertical tab, form feed, carriage return, space.
BLANKS = b"\x09\x0a\x0b\x0c\x0d\x20"


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, else the context's, else (tests, local mode) a new one."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        if known.isDefined():
            return known.get()
        where = tempfile.mkdtemp(prefix="mistcount-")
        spark.sparkContext.setCheckpointDir(f"file://{where}")
        return spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return where


_WRITTEN: dict[str, list[str]] = {}


def clean(spark: SparkSession) -> int:
    """Deletes the tables that this application has written so far; to be called when no result needs them any more."""
    jvm, paths = spark.sparkContext._jvm, _WRITTEN.pop(spark.sparkContext.applicationId, [])
    for path in paths:
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    return len(paths)


#: Whether Spark deletes an execution's shuffle files at its end.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def _freeing(spark: SparkSession) -> Iterator[None]:
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def written(df: DataFrame, what: str, codec: str = "zstd", free: bool = False) -> DataFrame:
    """The rows of df, written once as a table in the shared folder and read back: lineage ends there. free: the shuffle
    files of the write go at its end; otherwise they stay until the driver happens to collect its garbage."""
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/mistcount-{what}-{uuid.uuid4().hex}"
    _WRITTEN.setdefault(spark.sparkContext.applicationId, []).append(path)
    with _freeing(spark) if free else contextlib.nullcontext():
        df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def wrapped(docs: DataFrame) -> DataFrame:
    """docs as one struct column `row`, beside which an operator's own columns clash with nothing."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def running(df: DataFrame, order: list[Column], sums: dict[str, Column]) -> DataFrame:
    """df with the sums of some values over all rows before each one in a total order. Ranges of the order are summed
    each on its own; what lies before a range comes from a row a range. df must not hold the names given or `_range`."""
    given = df.select("*", *[x.alias(f"_of_{c}") for c, x in sums.items()])
    ranged = written(given.repartitionByRange(partitions(df.sparkSession), *order).withColumn("_range", F.spark_partition_id()), "ranges")
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # over a row a range
    offsets = ranged.groupBy("_range").agg(*[F.sum(f"_of_{c}").alias(f"_sum_{c}") for c in sums]).select("_range", *[F.sum(f"_sum_{c}").over(before).alias(f"_sum_{c}") for c in sums])
    inside = Window.partitionBy("_range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    found = ranged.join(F.broadcast(offsets), "_range")
    added = [(F.coalesce(F.col(f"_sum_{c}"), F.lit(0)) + F.coalesce(F.sum(f"_of_{c}").over(inside), F.lit(0))).alias(c) for c in sums]
    return found.select(*[F.col(f"`{c}`") for c in df.columns], *added)


def text_bytes(column: pa.Array) -> list[bytes | None]:
    """Values of an Arrow string or binary column as bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist() if not pa.types.is_binary(column.type) else column.to_pylist()


#: What a worker keeps from one task to the next: encoders, which take long to make. Tasks without need of them drop them,
#: as workers serve all operators one after the other.
KEPT: dict[tuple, object] = {}


def batches(rows: Iterator[pa.RecordBatch], size: int = 1024, keep: bool = False) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of at most `size` rows, to bound what is held as Python objects; when they are
    over, the worker, which serves further tasks, gives unused memory back. keep: the task uses what is KEPT."""
    if not keep:
        KEPT.clear()
    tidy()
    for batch in rows:
        for at in range(0, batch.num_rows, size):
            yield batch.slice(at, size)
    tidy()


def tidy() -> None:
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only glibc has it
        ctypes.CDLL(None).malloc_trim(0)


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (two multiply-xorshift rounds) of an unsigned array."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def word_count(text: Column) -> Column:
    """Number of maximal runs of anything but ASCII white space; 0 for null."""
    blank = F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+"))
    return F.coalesce(blank, F.lit(0)).cast("long")
