"""Operator 9: packing documents into fixed sequences by shortest-pack-first over the length histogram.

Documents longer than a sequence are cut into full pieces and a rest. Only the histogram of piece
lengths (at most ``SEQUENCE`` rows) reaches the driver. There lengths are placed longest first, each
into the emptiest kind of pack that still takes it; what is kept is the number of packs of each
pattern, never single packs, so the work depends on the histogram and not on the corpus. Pieces
find their place through their rank among the pieces of equal length. Ranks come from windows over
(length, bucket), with bucket offsets added, so that one frequent length is spread over many tasks; a piece's
bucket is drawn where its text is read and kept with it, so repeated rows are spread too.

Null text counts as empty: one piece of length 1. Very long texts give many pieces. Repeated rows, and rows with a
null doc_id, each get a place of their own; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from bisect import insort
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mapforge.llm.bpe import SLICE_ROWS, VOCABULARY, WordTable, vocabulary_path
from mapforge.llm.common import persist_table, table

SEQUENCE = 4096
END_ID = 2
RANK_BUCKETS = 64
#: Rows of (length, bucket) that may be broadcast, about 100 bytes each; longer sequences than 4096 are joined by shuffle.
BROADCAST_CELLS = 300_000


def pieces(docs: DataFrame, limit: int = SEQUENCE, text: str = "text", vocabulary: str = VOCABULARY, end_id: int = END_ID) -> DataFrame:
    """One row per piece of each document's ids (closed by ``end_id``): doc_id, start, length, ids_crc32, doc_tokens, bucket."""
    path, end = vocabulary_path(vocabulary), np.array([end_id], "<u4").tobytes()
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "bucket"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, nth = WordTable(path), 0
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                rows: list[tuple] = []
                for k, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ids = memoryview(words.encode(t) + end)
                    n = len(ids) // 4
                    for a in range(0, n, limit):
                        crc = zlib.crc32(ids[4 * a : 4 * (a + limit)])
                        rows.append((k, a, min(limit, n - a), crc, n, zlib.crc32(nth.to_bytes(8, "little"), crc) % RANK_BUCKETS))
                        nth += 1
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=names)

    return docs.select(F.col("doc_id").cast("long"), text).mapInArrow(run, ", ".join(f"{c} long" for c in names))


def plan_packs(histogram: dict[int, int], limit: int = SEQUENCE) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths in one pack) and how many packs follow each, shortest pack first.

    Lengths go longest first. Each count is spread over the open pattern with most room, as often as
    packs of that pattern exist; what no open pattern takes starts packs of its own.
    """
    open_by_room: dict[int, list[list]] = defaultdict(list)
    rooms: list[int] = []
    closed: list[tuple[tuple[int, ...], int]] = []

    def put(pattern: tuple[int, ...], room: int, n: int) -> None:
        if not room:
            closed.append((pattern, n))
            return
        if not open_by_room[room]:
            insort(rooms, room)
        open_by_room[room].append([pattern, n])

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left and rooms and rooms[-1] >= length:
            room = rooms[-1]
            pattern, n = open_by_room[room].pop()
            if not open_by_room[room]:
                rooms.pop()
            # as many pieces of this length as keep the pack the emptiest choice go in at once
            used = min(n, left)
            if used < n:
                put(pattern, room, n - used)
            put((*pattern, length), room - length, used)
            left -= used
        if left:
            put((length,), limit - length, left)
    return closed + [tuple(x) for room in rooms for x in open_by_room[room]]


def assign(pieces_df: DataFrame, limit: int = SEQUENCE) -> DataFrame:
    """``pieces_df`` with sequence_id and offset in place of bucket. Equal rows are interchangeable; every row gets its own place."""
    spark = pieces_df.sparkSession
    counts = persist_table(pieces_df.groupBy("length", "bucket").agg(F.count("*").alias("n")), "piece-counts")  # at most limit x RANK_BUCKETS rows
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most limit rows
    slots, filled, sequence = [], defaultdict(int), 0
    for pattern, n in plan_packs(histogram, limit):
        at = 0
        for length in pattern:
            slots.append((length, filled[length], filled[length] + n, sequence - filled[length], at))
            filled[length] += n
            at += length
        sequence += n
    # At most two patterns are made for each length, so slots are bounded by the sequence length as well.
    slots_df = spark.createDataFrame(slots, "length long, lo long, hi long, shift long, offset long")
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    # The pieces of one length share few slots; each (length, bucket) meets only those its ranks fall in.
    cells = base.join(slots_df, "length").where("lo < base + n and hi > base")
    cells = persist_table(cells.groupBy("length", "bucket", "base").agg(F.sort_array(F.collect_list(F.struct("lo", "hi", "shift", "offset"))).alias("slots")), "piece-cells")
    small = cells.agg(F.sum(F.size("slots"))).first()[0] or 0
    order = Window.partitionBy("length", "bucket").orderBy("doc_id", "start", "ids_crc32")
    ranked = pieces_df.withColumn("nth", F.row_number().over(order) - 1)
    placed = ranked.join(F.broadcast(cells) if small <= BROADCAST_CELLS else cells, ["length", "bucket"]).withColumn("rank", F.col("base") + F.col("nth"))
    slot = F.filter("slots", lambda s: (s["lo"] <= F.col("rank")) & (s["hi"] > F.col("rank")))[0]
    keep = [c for c in pieces_df.columns if c != "bucket"]
    return placed.withColumn("slot", slot).select(*keep, (F.col("rank") + F.col("slot.shift")).alias("sequence_id"), F.col("slot.offset").alias("offset"))


def pack(docs: DataFrame, limit: int = SEQUENCE, vocabulary: str = VOCABULARY) -> DataFrame:
    """Pieces of ``docs`` with their sequences; an empty table gives no rows."""
    return assign(persist_table(pieces(docs, limit, vocabulary=vocabulary), "pieces"), limit)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents", "doc_id", "text"))
