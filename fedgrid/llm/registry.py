"""Queries of the corpus operators and, where SQL expresses them, their SQL."""

from __future__ import annotations

from fedgrid.llm import (
    chat_format,
    decontamination,
    fingerprints,
    jaccard_join,
    language_id,
    line_dedup,
    mixing,
    pii,
    quality,
    substring_dedup,
)


def queries() -> dict:
    return {
        "op1_language_id": language_id.query,
        "op2_mixing": mixing.query,
        "op3_decontamination": decontamination.query,
        "op4_chat_format": chat_format.query,
        "op5_pii": pii.query,
        "op6_quality": quality.query,
        "op7_line_dedup": line_dedup.query,
        "op8_substring_dedup": substring_dedup.query,
        "op9_jaccard_join": jaccard_join.query,
        "op10_fingerprints": fingerprints.query,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op4_chat_format": chat_format.SQL,
        "op7_line_dedup": line_dedup.SQL,
        "op9_jaccard_join": jaccard_join.SQL,
    }
