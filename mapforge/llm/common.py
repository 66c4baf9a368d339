"""Helpers shared by the training-data operators.

Intermediate tables live in the folder that the cluster names in ``spark.checkpoint.dir``: every
executor can read them, so a lost executor costs a re-read and never a recomputation from scratch.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.operators.graph import components
from mapforge.sources.storage import drop as drop_table
from mapforge.sources.storage import shared_dir
from mapforge.sources.storage import stage as persist_table

__all__ = ["connected_components", "drop_table", "fresh_path", "persist_table", "shared_dir", "small_batches", "table"]


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@contextmanager
def small_batches(spark: SparkSession, rows: int = 500) -> Iterator[None]:
    """Arrow batches of at most ``rows`` rows for what runs inside: batches of long texts are held on both sides at once."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``(node, root)`` for each node of the undirected ``edges``; ``root`` is its component's least node."""
    return components(edges.select(F.col(a).alias("src"), F.col(b).alias("dst"))).withColumnsRenamed({"comp": "root"})
