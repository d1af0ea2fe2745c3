"""The subpackage's queries, with the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, embedding_dedup, language_id, minhash, packing, secrets, suffix_dedup, token_counts, toxicity, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_embedding_near_dedup": embedding_dedup.query,
        "op2_token_counts": token_counts.query,
        "op3_minhash_near_dedup": minhash.query,
        "op4_decontamination": decontamination.query,
        "op5_toxicity": toxicity.query,
        "op6_suffix_dedup": suffix_dedup.query,
        "op7_secret_scan": secrets.query,
        "op8_warc": warc.query,
        "op9_language_id": language_id.query,
        "op10_best_fit_packing": packing.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_embedding_near_dedup": embedding_dedup.ORACLE, "op8_warc": warc.ORACLE}
