"""Queries of the training-data operators and their SQL."""

from __future__ import annotations

from . import byte_bpe, decontaminate, html_extract, language_id, near_dup, quality_rules, substring_dedup, token_counts, toxicity, warc

QUERIES = {
    "op1_html_extract": html_extract.op1_html_extract,
    "op2_substring_dedup": substring_dedup.op2_substring_dedup,
    "op3_toxicity": toxicity.op3_toxicity,
    "op4_quality_rules": quality_rules.op4_quality_rules,
    "op5_near_dup": near_dup.op5_near_dup,
    "op6_byte_bpe": byte_bpe.op6_byte_bpe,
    "op7_token_counts": token_counts.op7_token_counts,
    "op8_decontaminate": decontaminate.op8_decontaminate,
    "op9_warc": warc.op9_warc,
    "op10_language_id": language_id.op10_language_id,
}

SQL = {"op2_substring_dedup": substring_dedup.ORACLE, "op5_near_dup": near_dup.ORACLE, "op9_warc": warc.ORACLE}


def queries() -> dict:
    import corpus_pipeline

    return QUERIES | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    import corpus_pipeline

    return SQL | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
