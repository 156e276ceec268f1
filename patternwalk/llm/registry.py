"""The operators' queries and their SQL twins."""

from __future__ import annotations

import corpus_pipeline
from patternwalk.llm import html_text, langid, licences, line_dedup, mixing, packing, progressive, quality, simhash, topk


def queries() -> dict:
    return {
        "op1_quality": quality.query,
        "op2_packing": packing.query,
        "op3_topk": topk.query,
        "op4_html": html_text.query,
        "op5_langid": langid.query,
        "op6_progressive": progressive.query,
        "op7_licences": licences.query,
        "op8_line_dedup": line_dedup.query,
        "op9_mixing": mixing.query,
        "op10_simhash": simhash.query,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_topk": topk.ORACLE,
        "op7_licences": licences.ORACLE,
        "op8_line_dedup": line_dedup.ORACLE,
        "op9_mixing": mixing.ORACLE,
    }
