"""Queries of the training-data operators, one for each, and their SQL where SQL can express them."""

from __future__ import annotations

from ringann.llm import chat, decontaminate, fingerprints, jaccard, language, lines, lm, mixing, secrets, suffix

QUERIES = {
    "op1_jaccard_join": jaccard.op1_jaccard_join,
    "op2_mixing": mixing.op2_mixing,
    "op3_language_id": language.op3_language_id,
    "op4_lm_score": lm.op4_lm_score,
    "op5_suffix_dedup": suffix.op5_suffix_dedup,
    "op6_chat_rotation": chat.op6_chat_rotation,
    "op8_fingerprints": fingerprints.op8_fingerprints,
    "op9_secrets": secrets.op9_secrets,
    "op7_line_dedup": lines.op7_line_dedup,
    "op10_decontaminate": decontaminate.op10_decontaminate,
}
ORACLES = {
    "op1_jaccard_join": jaccard.OP1_SQL,
    "op2_mixing": mixing.OP2_SQL,
    "op6_chat_rotation": chat.OP6_SQL,
    "op8_fingerprints": fingerprints.OP8_SQL,
    "op9_secrets": secrets.OP9_SQL,
    "op7_line_dedup": lines.OP7_SQL,
    "op10_decontaminate": decontaminate.OP10_SQL,
}
