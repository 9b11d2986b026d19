"""The registered queries of this subpackage and their DuckDB equivalents."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from gpart.llm import chat_format, decontamination, embedding_dedup, html_extraction, language_id, ngram_join, packing, sharding, token_counts, toxicity


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_decontamination": decontamination.op1_decontamination,
        "op2_language_id": language_id.op2_language_id,
        "op3_ngram_jaccard_join": ngram_join.op3_ngram_jaccard_join,
        "op4_sharding": sharding.op4_sharding,
        "op5_html_extraction": html_extraction.op5_html_extraction,
        "op6_token_counts": token_counts.op6_token_counts,
        "op7_toxicity": toxicity.op7_toxicity,
        "op8_embedding_near_dedup": embedding_dedup.op8_embedding_near_dedup,
        "op9_best_fit_packing": packing.op9_best_fit_packing,
        "op10_chat_formatting": chat_format.op10_chat_formatting,
    }


def oracle_sql() -> dict[str, str]:
    """Where SQL can express a query; the others are tested against brute force, exact round trips or held-out accuracy."""
    return {"op1_decontamination": decontamination.OP1_SQL, "op3_ngram_jaccard_join": ngram_join.OP3_SQL, "op8_embedding_near_dedup": embedding_dedup.OP8_SQL, "op10_chat_formatting": chat_format.OP10_SQL}
