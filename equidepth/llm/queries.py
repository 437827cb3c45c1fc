"""Queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from . import bottomk, decontaminate, html_crf, line_dedup, lm_scoring, mixing, probminhash, sharding, token_counts, toxicity

QUERIES = {
    "op1_bounded_ring": sharding.op1_query,
    "op2_pseudo_likelihood": lm_scoring.op2_query,
    "op3_html_crf": html_crf.op3_query,
    "op4_probminhash": probminhash.op4_query,
    "op5_source_mix": mixing.op5_query,
    "op6_simhash_leaks": decontaminate.op6_query,
    "op7_line_dedup": line_dedup.op7_query,
    "op8_token_cache": token_counts.op8_query,
    "op9_bottom_k": bottomk.op9_query,
    "op10_toxicity": toxicity.op10_query,
    "line_dedup_pages": line_dedup.pages_query,
}

ORACLE_SQL = {
    "op5_source_mix": mixing.OP5_SQL,
    "op7_line_dedup": line_dedup.OP7_SQL,
    "line_dedup_pages": line_dedup.PAGES_SQL,
}
