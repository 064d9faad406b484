"""Registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from . import chat, embdup, langid, mixing, neardup, quality, rules, sptok, substr, toxicity

QUERIES = {
    "op1_language_id": langid.op1,
    "op2_near_duplicates": neardup.op2,
    "op3_embedding_near_duplicates": embdup.op3,
    "op4_quality_classifier": quality.op4,
    "op5_sentencepiece_dropout": sptok.op5,
    "op6_source_mixing": mixing.op6,
    "op7_toxicity": toxicity.op7,
    "op8_chat_formatting": chat.op8,
    "op9_quality_rules": rules.op9,
    "op10_substring_dedup": substr.op10,
}

ORACLES = {
    "op2_near_duplicates": neardup.OP2_SQL,
    "op3_embedding_near_duplicates": embdup.OP3_SQL,
    "op6_source_mixing": mixing.OP6_SQL,
    "op8_chat_formatting": chat.OP8_SQL,
    "op9_quality_rules": rules.OP9_SQL,
    "op10_substring_dedup": substr.OP10_SQL,
}
