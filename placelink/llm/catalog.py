"""The named queries of this subpackage and their SQL."""

from __future__ import annotations

from placelink.llm import ann, boosting, chat, licenses, mixing, neardup, packing, repetition, reputation, toxicity

QUERIES = {
    "op1_near_duplicates": neardup.op1_near_duplicates,
    "op2_nearest": ann.op2_nearest,
    "op3_mixing": mixing.op3_mixing,
    "op4_licenses": licenses.op4_licenses,
    "op5_packing": packing.op5_packing,
    "op6_url_reputation": reputation.op6_url_reputation,
    "op7_chat": chat.op7_chat,
    "op8_toxicity": toxicity.op8_toxicity,
    "op9_repetition": repetition.op9_repetition,
    "op10_quality": boosting.op10_quality,
}
ORACLES = {"op1_near_duplicates": neardup.OP1_SQL, "op3_mixing": mixing.OP3_SQL, "op6_url_reputation": reputation.OP6_SQL, "op7_chat": chat.OP7_SQL, "op9_repetition": repetition.OP9_SQL}
