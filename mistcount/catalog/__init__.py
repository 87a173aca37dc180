"""All queries of the methods, baselines, measures, workloads and companion operators, by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import companions, comparisons, methods, oracles  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "flagship"]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four parties' overlapping items, each released at a budget of 3, united and fitted."""
    return methods.m09k(spark, sf_dir)
