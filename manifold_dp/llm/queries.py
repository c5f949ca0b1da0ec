"""Registered queries of the text operators: ``opN_<name>`` over whole tables."""

from __future__ import annotations

from . import chat, decontaminate, html, jaccard, linededup, pieces, quality, sql, substring, tokencount, topk

QUERIES = {
    "op1_decontaminate": decontaminate.query,
    "op2_line_dedup": linededup.query,
    "op3_token_counts": tokencount.query,
    "op4_chat_format": chat.query,
    "op5_pieces": pieces.query,
    "op6_quality": quality.query,
    "op7_substring_dedup": substring.query,
    "op8_jaccard_join": jaccard.query,
    "op9_topk": topk.query,
    "op10_page_text": html.query,
}

ORACLES = sql.ORACLES
