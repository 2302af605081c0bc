"""Queries and SQL of the operators, by name."""

from __future__ import annotations

from signpart.llm import chat_format, jaccard_join, language_id, line_dedup, lm_score, mixing, order_minhash, packing, substring_dedup, vector_dedup

QUERIES = {
    "op1_order_minhash": order_minhash.op1_order_minhash,
    "op2_vector_dedup": vector_dedup.op2_vector_dedup,
    "op3_mix_sources": mixing.op3_mix_sources,
    "op4_line_dedup": line_dedup.op4_line_dedup,
    "op5_lm_score": lm_score.op5_lm_score,
    "op6_chat_format": chat_format.op6_chat_format,
    "op7_jaccard_join": jaccard_join.op7_jaccard_join,
    "op8_language_id": language_id.op8_language_id,
    "op9_best_fit_packing": packing.op9_best_fit_packing,
    "op10_substring_dedup": substring_dedup.op10_substring_dedup,
}

ORACLES = {
    "op2_vector_dedup": vector_dedup.OP2_SQL,
    "op3_mix_sources": mixing.OP3_SQL,
    "op4_line_dedup": line_dedup.OP4_SQL,
    "op5_lm_score": lm_score.OP5_SQL,
    "op6_chat_format": chat_format.OP6_SQL,
    "op7_jaccard_join": jaccard_join.OP7_SQL,
    "op10_substring_dedup": substring_dedup.OP10_SQL,
}
