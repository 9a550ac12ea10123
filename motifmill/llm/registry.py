"""Queries of the training-data operators, and DuckDB SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from motifmill.llm import bpe, chat, decontaminate, licenses, pii, quality, sharding, simhash, sstable, substrings


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_license_scan": licenses.op1_license_scan,
        "op2_chat_format": chat.op2_chat_format,
        "op3_quality_rules": quality.op3_quality_rules,
        "op4_bpe": bpe.op4_bpe,
        "op5_pii": pii.op5_pii,
        "op6_decontaminate": decontaminate.op6_decontaminate,
        "op7_substrings": substrings.op7_substrings,
        "op8_simhash": simhash.op8_simhash,
        "op9_ring_sharding": sharding.op9_ring_sharding,
        "op10_token_shards": sstable.op10_token_shards,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_license_scan": licenses.OP1_SQL, "op3_quality_rules": quality.OP3_SQL, "op7_substrings": substrings.OP7_SQL}
