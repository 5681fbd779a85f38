"""Queries and SQL of the training-data operators, for __spark_entry__.py."""

from __future__ import annotations

from . import chat, decontaminate, htmltext, linededup, neardup, ordinal, packing, pii, quality, secretscan


def queries() -> dict:
    return {
        "op1_secret_scans": secretscan.op1_secret_scans,
        "op2_quality_rules": quality.op2_quality_rules,
        "op3_chat_formatting": chat.op3_chat_formatting,
        "op4_html_extraction": htmltext.op4_html_extraction,
        "op5_minhash_near_dedup": neardup.op5_minhash_near_dedup,
        "op6_line_dedup": linededup.op6_line_dedup,
        "op7_quality_classifier": ordinal.op7_quality_classifier,
        "op8_pii": pii.op8_pii,
        "op9_best_fit_packing": packing.op9_best_fit_packing,
        "op10_benchmark_decontamination": decontaminate.op10_benchmark_decontamination,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_chat_formatting": chat.OP3_SQL,
        "op5_minhash_near_dedup": neardup.OP5_SQL,
        "op6_line_dedup": linededup.OP6_SQL,
        "op10_benchmark_decontamination": decontaminate.OP10_SQL,
    }
