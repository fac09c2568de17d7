"""Queries and SQL of the training-data operators, by the names that the repository's entry registers."""

from __future__ import annotations

from terse.llm import chat_format, decontaminate, kneser_ney, line_dedup, nearest_toxic, quality_rules, shingle_join, source_mix, subword_quality, warc

QUERIES = {
    "op1_source_mix": source_mix.op1_query,
    "op2_warc": warc.op2_query,
    "op3_chat_format": chat_format.op3_query,
    "op4_nearest_toxic": nearest_toxic.op4_query,
    "op5_subword_quality": subword_quality.op5_query,
    "op6_decontaminate": decontaminate.op6_query,
    "op7_kneser_ney": kneser_ney.op7_query,
    "op8_shingle_join": shingle_join.op8_query,
    "op9_line_dedup": line_dedup.op9_query,
    "op10_quality_rules": quality_rules.op10_query,
}

ORACLE_SQL = {
    "op1_source_mix": source_mix.OP1_SQL,
    "op2_warc": warc.OP2_SQL,
    "op3_chat_format": chat_format.OP3_SQL,
    "op8_shingle_join": shingle_join.OP8_SQL,
    "op9_line_dedup": line_dedup.OP9_SQL,
}
