"""Queries of the operators in this folder, and their SQL where SQL can express them."""

from __future__ import annotations

from . import best_fit, decontaminate, embedding_join, jaccard, piece_counts, quality, substring, token_blocks, toxicity, url_filter


def queries() -> dict:
    return {
        "op1_token_blocks": token_blocks.query,
        "op2_ngram_jaccard": jaccard.query,
        "op3_url_filter": url_filter.query,
        "op4_toxicity": toxicity.query,
        "op5_best_fit_packing": best_fit.query,
        "op6_piece_counts": piece_counts.query,
        "op7_embedding_near_dedup": embedding_join.query,
        "op8_benchmark_decontamination": decontaminate.query,
        "op9_substring_dedup": substring.query,
        "op10_quality_votes": quality.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_url_filter": url_filter.sql(), "op7_embedding_near_dedup": embedding_join.sql()}
