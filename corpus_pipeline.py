"""The corpus pipeline: quality rules, n-gram Jaccard join, suffix-array dedup, mixing, packing.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last
return the columns of docs. Near-duplicates are told by five-word shingles and a similarity of 0.8.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from mistcount.llm import jaccard, mixing, packing, quality, substrings
from mistcount.llm.common import table, written

NEAR_PERCENT, NEAR_WORDS = 80, 5


def by_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return quality.quality_filter(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays."""
    return jaccard.one_of_each(docs, NEAR_PERCENT, NEAR_WORDS, bands=True)


def without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts lose the passages that other places of the corpus share."""
    return substrings.remove_repeated(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are brought to their target weights."""
    return mixing.mixed_documents(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents become windows of token ids."""
    return packing.pack(docs)


STAGES = [("quality_rules", by_quality), ("jaccard_join", one_of_each), ("suffix_dedup", without_repeats), ("mixing", mixed), ("packing", packed)]

#: SQL can't express the tokenizer of the last stage.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
