"""Queries of the corpus operators, by name, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import idfile, jaccard, langmodel, licenses, mixing, packing, quality, substrings, tokens, topk


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_exact_top_k": topk.op1_exact_top_k,
        "op2_quality_rules": quality.op2_quality_rules,
        "op3_license_scan": licenses.op3_license_scan,
        "op4_token_counts": tokens.op4_token_counts,
        "op5_token_ids": idfile.op5_token_ids,
        "op6_suffix_dedup": substrings.op6_suffix_dedup,
        "op7_mixing": mixing.op7_mixing,
        "op8_lm_scoring": langmodel.op8_lm_scoring,
        "op9_jaccard_join": jaccard.op9_jaccard_join,
        "op10_packing": packing.op10_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_top_k": topk.OP1_SQL, "op2_quality_rules": quality.OP2_SQL, "op3_license_scan": licenses.OP3_SQL, "op6_suffix_dedup": substrings.OP6_SQL, "op7_mixing": mixing.OP7_SQL, "op9_jaccard_join": jaccard.OP9_SQL}
