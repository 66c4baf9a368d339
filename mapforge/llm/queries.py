"""Queries of the training-data operators, for ``__spark_entry__.py``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from mapforge.llm import bpe, credentials, licenses, lines, media, neardup, oracles, packing, pii, toxicity, vectors


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_licenses": licenses.op1_licenses,
        "op2_pii": pii.op2_pii,
        "op3_lines": lines.op3_lines,
        "op4_toxicity": toxicity.op4_toxicity,
        "op5_embeddings": vectors.op5_embeddings,
        "op6_media": media.op6_media,
        "op7_near_duplicates": neardup.op7_near_duplicates,
        "op8_bpe": bpe.op8_bpe,
        "op9_packing": packing.op9_packing,
        "op10_secrets": credentials.op10_secrets,
    }


def oracle_sql() -> dict[str, str]:
    return dict(oracles.SQL)
