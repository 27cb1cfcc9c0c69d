"""Queries and SQL of the operators, by registered name."""

from __future__ import annotations

from . import chat, chunk_bpe, jaccard, packing, pii, quality, secrets, sharding, token_counts, vector_topk


def queries() -> dict:
    return {
        "op1_disclosure_sanitiser": pii.op1_disclosure_sanitiser,
        "op2_reply_trees": chat.op2_reply_trees,
        "op3_vector_approximation": vector_topk.op3_vector_approximation,
        "op4_chunk_reuse": chunk_bpe.op4_chunk_reuse,
        "op5_virtual_slots": sharding.op5_virtual_slots,
        "op6_sum_of_squares": packing.op6_sum_of_squares,
        "op7_line_first": quality.op7_line_first,
        "op8_secret_scan": secrets.op8_secret_scan,
        "op9_token_combinations": jaccard.op9_token_combinations,
        "op10_length_histogram": token_counts.op10_length_histogram,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_reply_trees": chat.OP2_SQL,
        "op3_vector_approximation": vector_topk.OP3_SQL,
        "op7_line_first": quality.OP7_SQL,
    }
