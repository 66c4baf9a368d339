"""Streaming surface: windows and sessions with watermarks, counters kept by upserts, and sinks that all executors share."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.sources.storage import shared_dir


def table_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's files as a stream."""
    path = f"{sf_dir}/{name}.parquet"
    return spark.readStream.schema(spark.read.parquet(path).schema).parquet(f"{path[:-1]}[t]")  # as a pattern, the path may be one file


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table_stream(spark, sf_dir, "events")


def event_windows(events: DataFrame, delay: str = "10 minutes", width: str = "1 hour") -> DataFrame:
    """Events per tumbling window and type; works on a stream or a table."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    return timed.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def run_available(spark: SparkSession, stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Drive a stream over what is there now and return the memory sink's table: for small results only."""
    q = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def run_to_table(spark: SparkSession, stream: DataFrame, name: str) -> DataFrame:
    """Drive an appending stream over what is there now into Parquet files of the shared folder, and read them back."""
    base = f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"
    q = stream.writeStream.outputMode("append").format("parquet").option("path", f"{base}/rows").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/rows")


def arrivals(spark: SparkSession, parts: list[DataFrame], name: str) -> DataFrame:
    """A stream in which the given tables arrive one after another, a micro-batch each (each is written as one file)."""
    base = f"{shared_dir(spark)}/arrivals-{name}-{uuid.uuid4().hex}"
    for k, part in enumerate(parts):
        part.coalesce(1).write.parquet(f"{base}/part={k}")
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(f"{base}/part=*")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """(user_id, start, n): a user's events without a gap; works on a stream or a table."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    found = timed.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return found.select("user_id", F.col("w.start").alias("start"), "n")


def distinct_within(events: DataFrame, keys: list[str], delay: str) -> DataFrame:
    """First arrivals of each key; state is kept for ``delay`` after the newest event and then goes."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    return timed.dropDuplicatesWithinWatermark(keys)


def run_batches(spark: SparkSession, stream: DataFrame, name: str, mode: str, each: Callable[[DataFrame, int], None]) -> None:
    """Drive a stream over what is there now, ``each`` taking every micro-batch with its number."""
    state = f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"
    q = stream.writeStream.outputMode(mode).option("checkpointLocation", state).foreachBatch(each).trigger(availableNow=True).start()
    q.awaitTermination()


def run_updates(spark: SparkSession, stream: DataFrame, name: str, keys: list[str], mode: str = "update") -> DataFrame:
    """The last update of each key: batches are kept by number, so a batch that runs again overwrites itself."""
    base = f"{shared_dir(spark)}/updates-{name}-{uuid.uuid4().hex}"
    run_batches(spark, stream, name, mode, lambda df, k: df.write.mode("overwrite").parquet(f"{base}/batch={k}"))
    rows = spark.read.option("basePath", base).parquet(base)
    others = [c for c in stream.columns if c not in keys]
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*others), "batch").alias("last"))
    return last.select(*keys, "last.*")


def upsert_counts(spark: SparkSession, stream: DataFrame, name: str, keys: list[str]) -> DataFrame:
    """(keys, support, changed): counters kept from batch to batch, ``changed`` where the last batch with rows moved them."""
    base = f"{shared_dir(spark)}/counters-{name}-{uuid.uuid4().hex}"
    done: dict[str, str] = {}

    def each(df: DataFrame, k: int) -> None:
        new = df.groupBy(*keys).agg(F.count("*").alias("support")).withColumn("changed", F.lit(True))
        if new.isEmpty():
            return
        if "last" in done:
            old = df.sparkSession.read.parquet(done["last"]).withColumn("changed", F.lit(False))
            new = old.unionByName(new).groupBy(*keys).agg(F.sum("support").alias("support"), F.max("changed").alias("changed"))
        new.write.mode("overwrite").parquet(f"{base}/version-{k}")
        done["last"] = f"{base}/version-{k}"

    run_batches(spark, stream, name, "append", each)
    return spark.read.parquet(done["last"])
