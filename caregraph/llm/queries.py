"""Queries of this subpackage for the entry module."""

from __future__ import annotations

from caregraph.llm import audio, chat_format, decontaminate, language_id, line_dedup, mixing, quality, simhash, substring_dedup, url_filter


def queries() -> dict:
    return {
        "op1_simhash_near_dedup": simhash.query,
        "op2_temperature_mixing": mixing.query,
        "op3_quality_classifier": quality.query,
        "op4_substring_dedup": substring_dedup.query,
        "op5_telephony_audio": audio.query,
        "op6_language_id": language_id.query,
        "op7_benchmark_decontamination": decontaminate.query,
        "op8_line_dedup": line_dedup.query,
        "op9_url_filter": url_filter.query,
        "op10_chat_format": chat_format.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op9_url_filter": url_filter.sql(), "op10_chat_format": chat_format.SQL}
