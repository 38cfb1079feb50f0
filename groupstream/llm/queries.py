"""The queries of this subpackage, one per operator, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chat, decontaminate, mixing, ngram, pipeline, quality, sharding, simhash, substring, suffixes, topk


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_substring_dedup": substring.query,
        "op2_top_k_search": topk.query,
        "op3_chat_format": chat.query,
        "op4_shard": sharding.query,
        "op5_suffix_dedup": suffixes.query,
        "op6_ngram_score": ngram.query,
        "op7_simhash_near_dedup": simhash.query,
        "op8_quality": quality.query,
        "op9_decontaminate": decontaminate.query,
        "op10_mix_sources": mixing.query,
        "pipeline": pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_top_k_search": topk.SQL, "op3_chat_format": chat.SQL, "op10_mix_sources": mixing.SQL}
