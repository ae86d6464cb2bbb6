"""Queries of the corpus operators and their SQL."""

from __future__ import annotations

from geohist.llm import bpe, exact, html, jaccard, packing, quality, substring, urls, winnow, wordpiece


def queries():
    return {
        "op1_jaccard_join": jaccard.op1_jaccard_join,
        "op2_exact_dedup": exact.op2_exact_dedup,
        "op3_fingerprint": winnow.op3_fingerprint,
        "op4_packing": packing.op4_packing,
        "op5_substring_dedup": substring.op5_substring_dedup,
        "op6_quality": quality.op6_quality,
        "op7_bpe": bpe.op7_bpe,
        "op8_html_text": html.op8_html_text,
        "op9_url_filter": urls.op9_url_filter,
        "op10_token_counts": wordpiece.op10_token_counts,
    }


def oracle_sql():
    return {"op2_exact_dedup": exact.OP2_SQL}
