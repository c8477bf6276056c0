"""Queries of the training-data operators and their SQL twins."""

from __future__ import annotations

from . import archives, chat_quotes, decontaminate, jaccard_join, line_dedup, piece_lattice, sharding, substring_dedup, topk, toxicity

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_toxicity": toxicity.op2_toxicity,
    "op3_decontaminate": decontaminate.op3_decontaminate,
    "op4_sentencepiece": piece_lattice.op4_sentencepiece,
    "op5_sharding": sharding.op5_sharding,
    "op6_warc": archives.op6_warc,
    "op7_chat_quotes": chat_quotes.op7_chat_quotes,
    "op8_topk": topk.op8_topk,
    "op9_jaccard_join": jaccard_join.op9_jaccard_join,
    "op10_substring_dedup": substring_dedup.op10_substring_dedup,
}

SQL = {
    "op1_line_dedup": line_dedup.OP1_SQL,
    "op7_chat_quotes": chat_quotes.OP7_SQL,
    "op8_topk": topk.OP8_SQL,
    "op9_jaccard_join": jaccard_join.OP9_SQL,
    "op10_substring_dedup": substring_dedup.OP10_SQL,
}
