"""Queries of the training-data operators, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from gradvb.llm import decontaminate, html_text, licenses, packing, quality, sharding, simhash, suffix_dedup, toxicity, vector_dedup


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_sharding": sharding.query,
        "op2_decontaminate": decontaminate.query,
        "op3_quality": quality.query,
        "op4_licenses": licenses.query,
        "op5_html": html_text.query,
        "op6_toxicity": toxicity.query,
        "op7_simhash": simhash.query,
        "op8_repeats": suffix_dedup.query,
        "op9_vectors": vector_dedup.query,
        "op10_packing": packing.query,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_decontaminate": decontaminate.ORACLE,
        "op8_repeats": suffix_dedup.ORACLE,
        "op9_vectors": vector_dedup.ORACLE,
    }
