"""Queries of the training-data operators, each over its whole table, and SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from graphdelta.llm import bpe, chat, counts, decontaminate, jaccard, lm, neighbours, quality, toxicity, urls


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality": quality.query,
        "op2_lm_score": lm.query,
        "op3_url_filter": urls.query,
        "op4_near_vectors": neighbours.query,
        "op5_ngram_jaccard": jaccard.query,
        "op6_toxicity": toxicity.query,
        "op7_decontaminate": decontaminate.query,
        "op8_token_counts": counts.query,
        "op9_bpe_round_trip": bpe.query,
        "op10_chat_format": chat.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op10_chat_format": chat.ORACLE}
