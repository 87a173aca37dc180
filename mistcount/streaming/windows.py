"""Sketches of windows of a stream.

Private windows are released once, when the watermark has passed their end (append mode): publishing a
window again would either spend its budget again or, with the same noise, show which bits came since.
Plain sketches may be kept and updated in any mode. State is a group's bitmaps, however many the items.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.budget import Flip
from ..functions.hashing import cell_of
from ..layout import Layout
from ..plans.arrow import all_bitmaps, flip_packed
from ..sources.io import record


def event_stream(spark: SparkSession, folder: str, schema, time: str = "ts", files_per_trigger: int = 1) -> DataFrame:
    """A file stream; watermarks need a TIMESTAMP, so the time is cast from the zoneless type."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return rows.withColumn(time, F.col(time).cast("timestamp"))


def rate_stream(spark: SparkSession, rows_per_second: int, time: str = "ts") -> DataFrame:
    """Rows numbered as time passes (item, ts): a load of a known number of distinct items, to try a stream's speed."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load().select(F.col("value").cast("string").alias("item"), F.col("timestamp").alias(time))


def window_bitmaps(stream: DataFrame, item: Column, layout: Layout, width: str, slide: str | None = None, late: str = "0 seconds", time: str = "ts", by: list[str] | None = None) -> DataFrame:
    """(window, by, bucket_no, bits) of tumbling or sliding windows; works on tables as well."""
    at = cell_of(item, layout).cast("long") + 1
    span = F.window(time, width, slide) if slide else F.window(time, width)
    rows = stream.withWatermark(time, late) if stream.isStreaming else stream
    return rows.where(item.isNotNull()).groupBy(span.alias("window"), *(by or []), F.bitmap_bucket_number(at).alias("bucket_no")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))


def session_counts(stream: DataFrame, gap: str, key: str, late: str = "0 seconds", time: str = "ts") -> DataFrame:
    """Rows of each key's sessions."""
    rows = stream.withWatermark(time, late) if stream.isStreaming else stream
    return rows.groupBy(F.session_window(time, gap).alias("window"), key).agg(F.count("*").alias("n_rows"))


def deduplicated(stream: DataFrame, keys: list[str], late: str, time: str = "ts") -> DataFrame:
    """Rows without those that repeat the keys within the watermark's reach."""
    if stream.isStreaming:
        return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)
    return stream.dropDuplicates(keys)


def private_windows(batch: DataFrame, layout: Layout, mechanism: Flip, key: str, release: str, by: list[str] | None = None, noise: str = "stream") -> DataFrame:
    """Noisy bitmaps of final windows (window_start, by, bucket_no, bits): what a sink may see. batch: window, by,
    bucket_no, bits. A window and group is a sketch of its own, with noise of its own."""
    names = ["window_start", *(by or [])]
    rows = batch.withColumn("window_start", F.col("window.start").cast("string"))
    return flip_packed(all_bitmaps(rows, rows.select(*names).distinct(), layout, names), mechanism, layout, key, release, names, noise)


def release_stream(
    bitmaps: DataFrame, layout: Layout, mechanism: Flip, key: str, release: str, path: str, ledger: str, checkpoint: str, by: list[str] | None = None, mode: str = "append", noise: str = "stream",
):
    """Starts a query that releases each window once, to partitions of path, and books it. Only append mode is allowed.

    release names this stream over these data; another stream, or a run over data that have changed, needs another
    one, as two releases of one name share their noise, and their difference would show the bits that differ.
    """
    if mode != "append":
        raise ValueError("a private window may be released once only, so the mode must be append")
    if not release:
        raise ValueError("a release needs a name of its own")
    names = ["window_start", *(by or [])]

    def sink(batch: DataFrame, epoch: int) -> None:
        # a batch that is tried again draws the same noise and replaces its own files and ledger entries
        noisy = private_windows(batch, layout, mechanism, key, release, by, noise)
        scope = F.concat_ws("/", *names)
        record(noisy.where("bucket_no = 1").select(F.concat_ws("/", F.lit(release), scope).alias("sketch_id"), F.lit(mechanism.epsilon).alias("eps"), scope.alias("scope")), ledger, f"{release}-{epoch}")
        noisy.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return bitmaps.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(sink).start()


def covering_days(table: DataFrame, time: str = "ts") -> int:
    """Days of lateness under which no row of a table is late, in whatever order its files are read."""
    span = table.agg(F.date_diff(F.max(time), F.min(time)).alias("n")).first()["n"]
    return (span or 0) + 1


def end_marker(table: DataFrame, late_days: int, width_days: int, item: str, time: str = "ts") -> DataFrame:
    """One row that takes the watermark past the end of the last window of a table. It needs an item, as a filter of
    null ones may come before the watermark; its own window lies past the watermark and is never released."""
    kinds = {f.name: f.dataType for f in table.schema}
    ts = F.max(time) + F.make_dt_interval(F.lit(late_days + 2 * width_days))
    other = lambda c: F.lit(0 if c == item else None).cast(kinds[c]).alias(c)
    return table.agg(ts.cast(kinds[time]).alias(time)).select(*[F.col(c) if c == time else other(c) for c in table.columns])
