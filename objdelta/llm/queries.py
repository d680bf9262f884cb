"""Queries and oracle SQL of the training-data operators."""

from __future__ import annotations

from . import decontaminate, jaccard_join, line_dedup, oracles, packing, pitman_yor, pivot_index, quality, suffix_dedup, toxicity, url_filter

QUERIES = {
    "op1_url_filter": url_filter.query,
    "op2_decontamination": decontaminate.query,
    "op3_pivot_index": pivot_index.query,
    "op4_toxicity": toxicity.query,
    "op5_pitman_yor": pitman_yor.query,
    "op6_jaccard_join": jaccard_join.query,
    "op7_line_dedup": line_dedup.query,
    "op8_packing": packing.query,
    "op9_suffix_dedup": suffix_dedup.query,
    "op10_quality": quality.query,
    "llm_url_rules": url_filter.rules_query,
}
ORACLES = {
    "op3_pivot_index": oracles.VECTORS,
    "op6_jaccard_join": oracles.SHINGLES,
    "op9_suffix_dedup": oracles.SUFFIXES,
    "op7_line_dedup": line_dedup.ORACLE,
    "llm_url_rules": url_filter.RULES_ORACLE,
}
