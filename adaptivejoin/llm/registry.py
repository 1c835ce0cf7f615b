"""Queries of this package by name, and the SQL of those that SQL can express."""

from __future__ import annotations

import corpus_pipeline

from adaptivejoin.llm import byte_pairs, chat, language, licences, lines, mixing, neighbours, personal, quality, simhash

QUERIES = {
    "op1_simhash": simhash.query,
    "op2_line_dedup": lines.query,
    "op3_licence_scan": licences.query,
    "op4_quality_rules": quality.query,
    "op5_nearest_neighbours": neighbours.query,
    "op6_language_id": language.query,
    "op7_chat_format": chat.query,
    "op8_byte_pairs": byte_pairs.query,
    "op9_personal_data": personal.query,
    "op10_mixing": mixing.query,
    "pipeline": corpus_pipeline.run,
}

ORACLES = {
    "op3_licence_scan": licences.ORACLE,
    "op4_quality_rules": quality.ORACLE,
    "op10_mixing": mixing.ORACLE,
}
