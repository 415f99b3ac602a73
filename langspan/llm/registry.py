"""Queries of this subpackage, each over its whole table, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, line_dedup, mixing, personal_data, phrases, preferences, quality, sharding, similarity_join, warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_rendezvous_sharding": sharding.query,
    "op2_site_quality": quality.query,
    "op3_consistent_phrases": phrases.query,
    "op4_line_windows": line_dedup.query,
    "op5_preference_pairs": preferences.query,
    "op6_source_mixing": mixing.query,
    "op7_skip_chain_personal_data": personal_data.query,
    "op8_simhash_decontamination": decontamination.query,
    "op9_adaptive_prefix_join": similarity_join.query,
    "op10_merkle_audit": warc.query,
}

ORACLES: dict[str, str] = {
    "op1_rendezvous_sharding": sharding.ORACLE,
    "op4_line_windows": line_dedup.ORACLE,
    "op5_preference_pairs": preferences.ORACLE,
    "op6_source_mixing": mixing.ORACLE,
    "op10_merkle_audit": warc.ORACLE,
}
