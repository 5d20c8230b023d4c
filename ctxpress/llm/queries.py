"""Queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from ctxpress.llm import decontaminate, embedding_dedup, html_main, language, licenses, mixing, simhash, suffix_dedup, toxicity, url_templates

QUERIES = {
    "op1_toxicity": toxicity.op1_toxicity,
    "op2_simhash_near_dedup": simhash.op2_simhash_near_dedup,
    "op3_language_id": language.op3_language_id,
    "op4_main_text": html_main.op4_main_text,
    "op5_license_scan": licenses.op5_license_scan,
    "op6_suffix_dedup": suffix_dedup.op6_suffix_dedup,
    "op7_url_filter": url_templates.op7_url_filter,
    "op8_mix_sources": mixing.op8_mix_sources,
    "op9_decontaminate": decontaminate.op9_decontaminate,
    "op10_embedding_near_dedup": embedding_dedup.op10_embedding_near_dedup,
}

ORACLE_SQL = {"op7_url_filter": url_templates.url_sql(), "op8_mix_sources": mixing.mixing_sql()}
