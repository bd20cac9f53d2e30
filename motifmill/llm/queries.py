"""The registered queries of this subpackage and the SQL they are checked with."""

from __future__ import annotations

from . import bpe, decontaminate, exact_dedup, lm_score, near_dedup, pii, substring_dedup, token_counts, toxicity, url_filter

QUERIES = {
    "op1_pii": pii.op1_pii,
    "op2_toxicity": toxicity.op2_toxicity,
    "op3_near_dedup": near_dedup.op3_near_dedup,
    "op4_url_filter": url_filter.op4_url_filter,
    "op5_decontaminate": decontaminate.op5_decontaminate,
    "op6_token_counts": token_counts.op6_token_counts,
    "op7_lm_score": lm_score.op7_lm_score,
    "op8_bpe": bpe.op8_bpe,
    "op9_substring_dedup": substring_dedup.op9_substring_dedup,
    "op10_exact_dedup": exact_dedup.op10_exact_dedup,
}

SQL = {
    "op3_near_dedup": near_dedup.SQL,
    "op9_substring_dedup": substring_dedup.SQL,
    "op10_exact_dedup": exact_dedup.SQL,
}
