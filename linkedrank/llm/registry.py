"""Queries of this subpackage and their DuckDB SQL."""

from __future__ import annotations

from linkedrank.llm import (
    chat_format, embedding_dedup, language_id, lm_scoring, minhash_dedup, mixing, packing,
    quality_classifier, quality_rules, url_filter,
)


def queries() -> dict:
    return {
        "op1_quality_classifier": quality_classifier.op1,
        "op2_best_fit_packing": packing.op2,
        "op3_embedding_dedup": embedding_dedup.op3,
        "op4_quality_rules": quality_rules.op4,
        "op5_url_filter": url_filter.op5,
        "op6_minhash_dedup": minhash_dedup.op6,
        "op7_chat_format": chat_format.op7,
        "op8_language_id": language_id.op8,
        "op9_lm_scoring": lm_scoring.op9,
        "op10_source_mixing": mixing.op10,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_embedding_dedup": embedding_dedup.oracle_sql(),
        "op4_quality_rules": quality_rules.oracle_sql(),
        "op5_url_filter": url_filter.oracle_sql(),
        "op6_minhash_dedup": minhash_dedup.oracle_sql(),
        "op7_chat_format": chat_format.oracle_sql(),
        "op10_source_mixing": mixing.oracle_sql(),
    }
