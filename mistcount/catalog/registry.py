"""Where queries and their SQL are put, and where queries put tables."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def shared_path(spark: SparkSession, what: str) -> str:
    """A new place in the folder that all executors share: spark.checkpoint.dir, else the context's checkpoint
    folder, else (local mode only) a temporary one."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        where = known.get() if known.isDefined() else "file://" + tempfile.mkdtemp(prefix="mistcount-")
    return f"{where.rstrip('/')}/mistcount-{what}-{uuid.uuid4().hex}"


def oracle(name: str, sql: str) -> None:
    """SQL of a query that is registered already."""
    if name not in QUERIES or name in ORACLES:
        raise ValueError(f"{name} has no query, or SQL already")
    ORACLES[name] = sql


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put
