"""Queries of the training-data operators and the DuckDB SQL that states their results."""

from __future__ import annotations

from skewroute.llm import chat, mixing, packing, quality, simhash, substring, telephony, topk, toxicity, warc

QUERIES = {
    "op1_toxicity": toxicity.op1_toxicity,
    "op2_warc": warc.op2_warc,
    "op3_mixing": mixing.op3_mixing,
    "op4_simhash": simhash.op4_simhash,
    "op5_chat": chat.op5_chat,
    "op6_packing": packing.op6_packing,
    "op7_substring": substring.op7_substring,
    "op8_quality": quality.op8_quality,
    "op9_telephony": telephony.op9_telephony,
    "op10_topk": topk.op10_topk,
}

ORACLES: dict[str, str] = {
    "op2_warc": warc.ORACLE,
    "op5_chat": chat.ORACLE,
    "op10_topk": topk.ORACLE,
}
