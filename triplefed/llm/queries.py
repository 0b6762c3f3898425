"""The queries of the ten operators, by number, and the SQL that checks them where SQL can say it."""

from __future__ import annotations

from triplefed.llm import chat_format, license_scan, mixing, near_duplicates, packing, quality_rules, token_count, toxicity, url_filter, vector_search

QUERIES = {
    "op1_url_filter": url_filter.query,
    "op2_source_mixing": mixing.query,
    "op3_chat_format": chat_format.query,
    "op4_toxicity": toxicity.query,
    "op5_license_scan": license_scan.query,
    "op6_near_duplicates": near_duplicates.query,
    "op7_token_counts": token_count.query,
    "op8_best_fit_packing": packing.query,
    "op9_quality_rules": quality_rules.query,
    "op10_vector_search": vector_search.query,
}
ORACLES = {
    "op1_url_filter": url_filter.ORACLE,
    "op2_source_mixing": mixing.ORACLE,
    "op3_chat_format": chat_format.ORACLE,
    "op10_vector_search": vector_search.ORACLE,
}
