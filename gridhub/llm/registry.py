"""Queries of this subpackage and their SQL."""

from __future__ import annotations

from gridhub.llm import chat, exact, lmscore, mixing, neighbors, packing, quality, simhash, tokens, toxicity

QUERIES = {
    "op1_chat_format": chat.op1_chat_format,
    "op2_simhash_groups": simhash.op2_simhash_groups,
    "op3_toxicity": toxicity.op3_toxicity,
    "op4_source_mixing": mixing.op4_source_mixing,
    "op5_lm_scores": lmscore.op5_lm_scores,
    "op6_packing": packing.op6_packing,
    "op7_token_counts": tokens.op7_token_counts,
    "op8_exact_dedup": exact.op8_exact_dedup,
    "op9_quality": quality.op9_quality,
    "op10_top_k": neighbors.op10_top_k,
}

SQL = {
    "op1_chat_format": chat.OP1_SQL,
    "op4_source_mixing": mixing.OP4_SQL,
    "op8_exact_dedup": exact.OP8_SQL,
    "op10_top_k": neighbors.OP10_SQL,
}
