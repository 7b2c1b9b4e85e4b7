"""Registered queries of the operators and the SQL that checks them."""

from __future__ import annotations

from graphviews.llm import ann, chat, decontamination, langid, line_dedup, lm_scoring, minhash, packing, toxicity, warc

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_retrieval_packing": packing.op2_retrieval_packing,
    "op3_nearest_neighbours": ann.op3_nearest_neighbours,
    "op4_language_id": langid.op4_language_id,
    "op5_warc_convert": warc.op5_warc_convert,
    "op6_chat_format": chat.op6_chat_format,
    "op7_decontaminate": decontamination.op7_decontaminate,
    "op8_lm_score": lm_scoring.op8_lm_score,
    "op9_minhash_dedup": minhash.op9_minhash_dedup,
    "op10_toxicity_chain": toxicity.op10_toxicity_chain,
}

ORACLE_SQL = {
    "op1_line_dedup": line_dedup.OP1_SQL,
    "op5_warc_convert": warc.OP5_SQL,
    "op6_chat_format": chat.OP6_SQL,
    "op7_decontaminate": decontamination.OP7_SQL,
    "op9_minhash_dedup": minhash.OP9_SQL,
}
