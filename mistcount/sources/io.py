"""Tables, sketch catalogues and the budget ledger."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..layout import Layout

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: A released sketch: a row for each of its bitmaps' rows.
SKETCHES = (
    "sketch_id string, grp string, layout struct<kind: string, buckets: int, levels: int, family: string, seed: int>, "
    "mechanism struct<kind: string, p: double, q: double, eps: double>, eps_effective double, lineage array<string>, n_sources int, cell int, bit int"
)
LEDGER = "release_id string, sketch_id string, eps double, scope string, released_at timestamp"


def read_table(spark: SparkSession, where: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{where}/{name}.parquet")


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None) -> DataFrame:
    """parquet, orc, json, csv (with a header) or text; a schema is taken as given, never inferred from the rows of text formats."""
    reader = spark.read.format(kind)
    if schema:
        reader = reader.schema(schema)
    return reader.option("header", True).load(path) if kind == "csv" else reader.load(path)


def layout_column(layout: Layout):
    return F.struct(F.lit(layout.kind).alias("kind"), F.lit(layout.buckets).alias("buckets"), F.lit(layout.levels).alias("levels"), F.lit(layout.family).alias("family"), F.lit(layout.seed).alias("seed"))


def catalogued(cells: DataFrame, layout: Layout, eps, kind: str, p, q, grp: str, release: str, lineage=None) -> DataFrame:
    """Noisy cells as catalogue rows; a sketch is its own ancestor unless it was merged."""
    sketch_id = F.concat_ws("/", F.lit(release), F.col(grp).cast("string"))
    own = F.array(sketch_id) if lineage is None else lineage
    mechanism = F.struct(F.lit(kind).alias("kind"), F.lit(p).cast("double").alias("p"), F.lit(q).cast("double").alias("q"), F.lit(eps).cast("double").alias("eps"))
    return cells.select(sketch_id.alias("sketch_id"), F.col(grp).cast("string").alias("grp"), layout_column(layout).alias("layout"), mechanism.alias("mechanism"), F.lit(eps).cast("double").alias("eps_effective"), own.alias("lineage"), F.lit(1).alias("n_sources"), "cell", F.col("bit").cast("int").alias("bit"))


def described(cells: DataFrame, layout: Layout, kind: str, grp: str, release: str, by: list[str] | None = None, eps: str = "eps") -> DataFrame:
    """A catalogue row (by, sketch_id, layout, mechanism, lineage) for each released sketch of cells (by, grp, cell, bit, eps):
    what a merge needs to know of it. A sketch is told by its release and group."""
    sketch_id = F.concat_ws("/", F.lit(release), F.col(grp).cast("string"))
    mechanism = F.struct(F.lit(kind).alias("kind"), F.col(eps).alias("eps"))
    return cells.where("cell = 0").select(*(by or []), sketch_id.alias("sketch_id"), layout_column(layout).alias("layout"), mechanism.alias("mechanism"), F.array(sketch_id).alias("lineage"))


def _replace(rows: DataFrame, path: str, release: str) -> None:
    rows.withColumn("release", F.lit(release)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("release").parquet(path)


def write_sketches(rows: DataFrame, path: str, release: str, ledger: str) -> None:
    """A release is a partition of its own, of the sketches and of the ledger; writing it again replaces both, so a
    retry spends nothing. The ledger is written first: a budget may be booked in vain, never spent unbooked. Rows of
    cells compress to about their bits."""
    record(heads(rows).select("sketch_id", F.col("eps_effective").alias("eps"), F.col("grp").alias("scope")), ledger, release)
    _replace(rows, path, release)


def record(spending: DataFrame, ledger: str, release: str) -> None:
    """Books a release: sketch_id, eps, scope."""
    entries = spending.select(F.lit(release).alias("release_id"), "sketch_id", F.col("eps").cast("double").alias("eps"), F.col("scope").cast("string").alias("scope"), F.current_timestamp().alias("released_at"))
    _replace(entries, ledger, release)


def read_ledger(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(LEDGER + ", release string").parquet(path).drop("release")


def read_sketches(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SKETCHES + ", release string").parquet(path)


def heads(rows: DataFrame) -> DataFrame:
    """One row a sketch."""
    return rows.where("cell = 0").drop("cell", "bit")


def spent(ledger: DataFrame, by: str = "scope") -> DataFrame:
    """Budget spent: releases over the same items add up. The budget of a merged sketch is no spending."""
    return ledger.groupBy(by).agg(F.sum("eps").alias("eps_spent"), F.count("*").alias("releases"))


def latest(ledger: DataFrame, at: DataFrame, key: str = "scope", time: str = "at", keep: list[str] | None = None) -> DataFrame:
    """For each row of `at` (key, time, keep) the last ledger entry at or before it, ties to the larger release_id:
    both sides in one order by key, no range join. Keys are users or scopes, so a window holds one such's entries."""
    keep = keep or []
    a = at.select(key, F.col(time).alias("t"), F.lit(1).alias("asks"), F.lit(None).cast("string").alias("release_id"), *keep)
    b = ledger.select(key, F.col("released_at").alias("t"), F.lit(0).alias("asks"), "release_id")
    w = Window.partitionBy(key).orderBy("t", "asks", "release_id").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("last", F.last("release_id", ignorenulls=True).over(w))
    return both.where("asks = 1").select(key, F.col("t").alias(time), *keep, F.col("last").alias("release_id"))


def describe(layout: Layout) -> str:
    return json.dumps({"kind": layout.kind, "buckets": layout.buckets, "levels": layout.levels, "family": layout.family, "seed": layout.seed})
