"""The operators' queries by name, and the SQL that gives the same rows where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from cellfleet.llm import embeddings, html_main, mixing, packing, quality, secrets, simhash, substrings, token_counts, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mix_sources": mixing.op1_mix_sources,
        "op2_token_counts": token_counts.op2_token_counts,
        "op3_pack": packing.op3_pack,
        "op4_main_text": html_main.op4_main_text,
        "op5_embedding_near_dedup": embeddings.op5_embedding_near_dedup,
        "op6_simhash_near_dedup": simhash.op6_simhash_near_dedup,
        "op7_quality_rules": quality.op7_quality_rules,
        "op8_secret_scan": secrets.op8_secret_scan,
        "op9_substring_dedup": substrings.op9_substring_dedup,
        "op10_warc_index": warc.op10_warc_index,
    }


def oracle_sql() -> dict[str, str]:
    """For the operators that SQL can express whole; the others are tested against brute force in tests/llm."""
    return {
        "op1_mix_sources": mixing.ORACLE_SQL,
        "op5_embedding_near_dedup": embeddings.ORACLE_SQL,
        "op9_substring_dedup": substrings.ORACLE_SQL,
        "op10_warc_index": warc.ORACLE_SQL,
    }
