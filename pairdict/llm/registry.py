"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import decontaminate, language, language_model, line_dedup, oracles, pii, quality, sharding, simhash, subwords, topk


def queries() -> dict:
    return {
        "op1_language": language.query,
        "op2_sharding": sharding.query,
        "op3_pii": pii.query,
        "op4_topk": topk.query,
        "op5_line_dedup": line_dedup.query,
        "op6_simhash": simhash.query,
        "op7_subwords": subwords.query,
        "op8_quality": quality.query,
        "op9_decontaminate": decontaminate.query,
        "op10_language_model": language_model.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_topk": oracles.TOPK, "op5_line_dedup": oracles.LINES, "op9_decontaminate": oracles.BENCHMARK}
