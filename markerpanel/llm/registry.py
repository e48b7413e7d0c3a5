"""Queries and SQL of the training-data operators."""

from __future__ import annotations

from markerpanel.llm import archives, decontamination, line_dedup, near_duplicates, piece_codec, quality_rules, suffix_dedup, token_counts, toxicity, url_filters


def queries() -> dict:
    return {
        "op1_suffix_dedup": suffix_dedup.op1,
        "op2_sentencepiece": piece_codec.op2,
        "op3_warc": archives.op3,
        "op4_token_counts": token_counts.op4,
        "op5_quality_rules": quality_rules.op5,
        "op6_near_duplicates": near_duplicates.op6,
        "op7_toxicity": toxicity.op7,
        "op8_url_filters": url_filters.op8,
        "op9_line_dedup": line_dedup.op9,
        "op10_decontamination": decontamination.op10,
    }


def oracle_sql() -> dict:
    return {
        "op3_warc": archives.OP3_SQL,
        "op5_quality_rules": quality_rules.OP5_SQL,
        "op6_near_duplicates": near_duplicates.OP6_SQL,
        "op10_decontamination": decontamination.OP10_SQL,
    }
