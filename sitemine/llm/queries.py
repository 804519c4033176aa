"""Queries of the corpus operators, one per operator, with SQL twins where SQL can say it."""

from __future__ import annotations

from sitemine.llm import bpe, chat_format, embedding_dedup, language_id, line_dedup, mixing, mpeg_audio, quality_lm, simhash, url_rules

QUERIES = {
    "op1_mpeg_audio": mpeg_audio.op1_mpeg_audio,
    "op2_embedding_dedup": embedding_dedup.op2_embedding_dedup,
    "op3_url_rules": url_rules.op3_url_rules,
    "op4_bpe": bpe.op4_bpe,
    "op5_mixing": mixing.op5_mixing,
    "op6_chat_format": chat_format.op6_chat_format,
    "op7_line_dedup": line_dedup.op7_line_dedup,
    "op8_simhash": simhash.op8_simhash,
    "op9_quality_lm": quality_lm.op9_quality_lm,
    "op10_language_id": language_id.op10_language_id,
    "url_fixed_rules": url_rules.url_fixed_rules,
}
ORACLES = {
    "op1_mpeg_audio": mpeg_audio.ORACLE,
    "op2_embedding_dedup": embedding_dedup.ORACLE,
    "op5_mixing": mixing.ORACLE,
    "op6_chat_format": chat_format.ORACLE,
    "op7_line_dedup": line_dedup.ORACLE,
    "url_fixed_rules": url_rules.FIXED_ORACLE,
}
