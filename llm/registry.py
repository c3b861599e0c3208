"""The queries of the operators in this subpackage, and the SQL for those that SQL can express."""

from __future__ import annotations

from llm import decontamination, html_text, language_id, near_duplicates, neighbours, packing, quality, sharding, suffix_dedup, toxicity


def queries() -> dict:
    return {
        "op2_suffix_dedup": suffix_dedup.op2,
        "op3_quality": quality.op3,
        "op9_neighbours": neighbours.op9,
        "op10_packing": packing.op10,
        "op1_near_duplicates": near_duplicates.op1,
        "op4_decontamination": decontamination.op4,
        "op5_sharding": sharding.op5,
        "op6_html_text": html_text.op6,
        "op7_language_id": language_id.op7,
        "op8_toxicity": toxicity.op8,
    }


def oracle_sql() -> dict[str, str]:
    return {}
