"""Queries of the training-data operators and their SQL."""

from __future__ import annotations

from . import chatfmt, decontam, embdedup, langid, linededup, maxent, mixing, neardup, quality, suffixdedup
from .common import table


def queries() -> dict:
    return {
        "op1_language_id": lambda s, d: langid.language_id(table(s, d, "documents")),
        "op2_near_duplicates": lambda s, d: neardup.near_duplicates(table(s, d, "documents")),
        "op3_lm_scores": lambda s, d: maxent.lm_scores(table(s, d, "documents")),
        "op4_line_dedup": lambda s, d: linededup.line_query(table(s, d, "documents")),
        "op5_decontamination": lambda s, d: decontam.decontam_query(table(s, d, "documents"), table(s, d, "benchmark")),
        "op6_quality_rules": lambda s, d: quality.quality_query(table(s, d, "documents"), table(s, d, "labels")),
        "op7_repeated_substrings": lambda s, d: suffixdedup.substring_query(table(s, d, "documents")),
        "op8_source_mixing": lambda s, d: mixing.mixing_query(table(s, d, "documents")),
        "op9_chat_format": lambda s, d: chatfmt.chat_query(table(s, d, "conversations")),
        "op10_embedding_near_duplicates": lambda s, d: embdedup.link_vectors(table(s, d, "embeddings")),
    }


def oracle_sql() -> dict[str, str]:
    return {"op10_embedding_near_duplicates": embdedup.ORACLE, "op2_near_duplicates": neardup.ORACLE, "op5_decontamination": decontam.ORACLE, "op4_line_dedup": linededup.ORACLE, "op9_chat_format": chatfmt.ORACLE}
