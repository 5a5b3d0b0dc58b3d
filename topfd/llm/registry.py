"""The queries of this subpackage and their SQL, for __spark_entry__."""

from __future__ import annotations

from . import ann, exact_search, html_extraction, language_id, mixing, near_dedup, packing, substring_dedup, token_counts, url_filter

QUERIES = {
    "op1_exact_top_k": exact_search.op1_exact_top_k,
    "op2_language_id": language_id.op2_language_id,
    "op3_substring_dedup": substring_dedup.op3_substring_dedup,
    "op4_source_mix": mixing.op4_source_mix,
    "op5_url_filter": url_filter.op5_url_filter,
    "op6_token_counts": token_counts.op6_token_counts,
    "op7_near_dedup": near_dedup.op7_near_dedup,
    "op8_packing": packing.op8_packing,
    "op9_html_extraction": html_extraction.op9_html_extraction,
    "op10_ann": ann.op10_ann,
}
ORACLES = {"op1_exact_top_k": exact_search.ORACLE, "op7_near_dedup": near_dedup.ORACLE, "op3_substring_dedup": substring_dedup.ORACLE, "op4_source_mix": mixing.ORACLE, "op5_url_filter": url_filter.ORACLE}
