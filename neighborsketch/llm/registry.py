"""Queries and DuckDB SQL of the training-data operators."""

from __future__ import annotations

from . import byte_bpe, chat_format, decontamination, exact_dedup, language_id, line_dedup, ngram_join, quality, secret_scan, sharding

QUERIES = {
    "op1_exact_dedup": exact_dedup.op1_exact_dedup,
    "op2_chat_format": chat_format.op2_chat_format,
    "op3_byte_bpe": byte_bpe.op3_byte_bpe,
    "op4_quality": quality.op4_quality,
    "op5_secret_scan": secret_scan.op5_secret_scan,
    "op6_line_dedup": line_dedup.op6_line_dedup,
    "op7_language_id": language_id.op7_language_id,
    "op8_ngram_join": ngram_join.op8_ngram_join,
    "op9_decontamination": decontamination.op9_decontamination,
    "op10_sharding": sharding.op10_sharding,
}

ORACLES = {
    "op1_exact_dedup": exact_dedup.ORACLE,
    "op2_chat_format": chat_format.ORACLE,
    "op6_line_dedup": line_dedup.ORACLE,
}
