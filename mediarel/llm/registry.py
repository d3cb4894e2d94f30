"""Queries of this subpackage and their oracle SQL."""

from __future__ import annotations

from mediarel.llm import bpe, html_text, language, licenses, mixing, near_dup, neighbours, quality, token_counts, token_files

_QUERIES = {
    "op1_quality_rules": quality.op1_quality_rules,
    "op2_near_duplicates": near_dup.op2_near_duplicates,
    "op3_language_id": language.op3_language_id,
    "op4_bpe_codec": bpe.op4_bpe_codec,
    "op5_token_files": token_files.op5_token_files,
    "op6_token_counts": token_counts.op6_token_counts,
    "op7_nearest_neighbours": neighbours.op7_nearest_neighbours,
    "op8_html_text": html_text.op8_html_text,
    "op9_license_scan": licenses.op9_license_scan,
    "op10_mix_sources": mixing.op10_mix_sources,
}

_ORACLE_SQL = {"op2_near_duplicates": near_dup.OP2_SQL, "op7_nearest_neighbours": neighbours.OP7_SQL, "op10_mix_sources": mixing.OP10_SQL}


def queries() -> dict:
    return dict(_QUERIES)


def oracle_sql() -> dict:
    return dict(_ORACLE_SQL)
