"""The queries of this folder and the SQL that states the same results."""

from __future__ import annotations

from seedrank.llm import chat, decontam, html, language, lm, neardup, packing, quality, secrets, sharding

QUERIES = {
    "op1_quality_rules": quality.op1_quality,
    "op2_language": language.op2_language,
    "op3_shard_groups": sharding.op3_sharding,
    "op4_near_duplicates": neardup.op4_near_duplicates,
    "op5_pack_sequences": packing.op5_packing,
    "op6_decontaminate": decontam.op6_decontam,
    "op7_html_text": html.op7_html,
    "op8_chat_format": chat.op8_chat,
    "op9_secrets": secrets.op9_secrets,
    "op10_lm_scores": lm.op10_lm,
}
ORACLES = {
    "op1_quality_rules": quality.OP1_SQL,
    "op6_decontaminate": decontam.OP6_SQL,
    "op10_lm_scores": lm.OP10_SQL,
}
