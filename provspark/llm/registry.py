"""Queries and SQL of the pipeline operators, gathered for __spark_entry__."""

from __future__ import annotations

from provspark.llm import chunks, decontaminate, htmltext, langid, media, mixing, neardup, tokens, warc

QUERIES = {
    "op1_near_duplicates": neardup.op1_near_duplicates,
    "op2_tokens": tokens.op2_tokens,
    "op3_mixing": mixing.op3_mixing,
    "op4_token_counts": tokens.op4_token_counts,
    "op5_language_id": langid.op5_language_id,
    "op6_substring_dedup": chunks.op6_substring_dedup,
    "op7_decontamination": decontaminate.op7_decontamination,
    "op8_html_text": htmltext.op8_html_text,
    "op9_warc": warc.op9_warc,
    "op10_media": media.op10_media,
}

ORACLES = {
    "op1_near_duplicates": neardup.OP1_SQL,
    "op9_warc": warc.OP9_SQL,
}
