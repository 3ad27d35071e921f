"""Registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from . import chat, decontaminate, language, licences, main_text, near_duplicates, neighbours, packing, quality, token_counts

QUERIES = {
    "op1_language": language.op1_language,
    "op2_quality": quality.op2_quality,
    "op3_chat": chat.op3_chat,
    "op4_packing": packing.op4_packing,
    "op5_token_counts": token_counts.op5_token_counts,
    "op6_main_text": main_text.op6_main_text,
    "op7_licences": licences.op7_licences,
    "op8_near_duplicates": near_duplicates.op8_near_duplicates,
    "op9_neighbours": neighbours.op9_neighbours,
    "op10_decontamination": decontaminate.op10_decontamination,
}

ORACLE: dict[str, str] = {
    "op3_chat": chat.OP3_SQL,
    "op7_licences": licences.OP7_SQL,
    "op8_near_duplicates": near_duplicates.OP8_SQL,
    "op10_decontamination": decontaminate.OP10_SQL,
}
