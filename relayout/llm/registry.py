"""Queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from relayout.llm import decontam, jaccard, language_id, packing, quality, quotes, substring_index, suffix_dedup, topk, url_filter

QUERIES = {
    "op1_language_id": language_id.query,
    "op2_suffix_dedup": suffix_dedup.query,
    "op3_packing": packing.query,
    "op4_substring_dedup": substring_index.query,
    "op5_decontamination": decontam.query,
    "op6_quality": quality.query,
    "op7_url_filter": url_filter.query,
    "op8_quotation_linking": quotes.query,
    "op9_jaccard_join": jaccard.query,
    "op10_exact_topk": topk.query,
}
ORACLES = {
    "op4_substring_dedup": substring_index.ORACLE,
    "op7_url_filter": url_filter.ORACLE,
    "op9_jaccard_join": jaccard.ORACLE,
    "op10_exact_topk": topk.ORACLE,
}
