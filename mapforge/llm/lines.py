"""Operator 3: line deduplication by a deletion-neighbourhood join.

Two lines are the same when equal, or when their edit bound (insertion, deletion or substitution of a code point)
allows: a line may differ by one edit for every ``MIN_CHARS`` code points that both lines have, one at most. A line is removed
when an earlier one is the same; earlier means a smaller (doc_id, hash of text, line number), null ids first. Blank lines
always stay. Near matches are looked for between distinct lines, by their first places.

All variants of a line within the bound are its deletions of one character. They are emitted as hashed
keys, in three steps that lose no match:

1. One edit leaves the line's first or second half whole. Lines that share a half (at the cut that fits
   either length) with another distinct line go on; nearly all others end here.
2. For those, one key per deleted character of the other half: the shared half and the place belong to
   the key. Lines of one length that agree in such a key differ at that place only; a line that equals
   a deletion of a longer one is found by its own key. All keys of a line come from one running sum over its
   code points, so a line of a million of them costs a million keys and no more.
3. The earliest line of every key is compared with each of its other lines around the place of the edit.

Rows that repeat a doc_id and text are one document here and are treated alike. Null text stays null, an empty one
empty; an empty table gives no rows. Columns other than ``text``, ``removed`` and ``removed_near`` stay.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import persist_table, table

MIN_CHARS = 16
BROADCAST_ROWS = 1_000_000


def _lines(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, pos, line) of lines that are not blank."""
    cut = docs.where("text is not null").select("doc_id", F.xxhash64("text").alias("mark"), F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    return cut.where(F.col("line").rlike(r"\S"))


def _hash(line: Column) -> Column:
    return F.struct(F.xxhash64(line).alias("a"), F.xxhash64(F.lit(5), line).alias("b"))


def _half_keys(line: Column, n: Column) -> list[Column]:
    """Keys of the halves of a line of ``n`` code points: as the longer (or equal) partner, and as the shorter one."""

    def keys(length: Column) -> list[Column]:
        half = F.floor(length / 2).cast("int")
        rest = (length - half).cast("int")
        return [F.xxhash64(F.lit(1), length, F.substring(line, F.lit(1), half)), F.xxhash64(F.lit(2), length, F.right(line, rest))]

    return keys(n) + keys(n + 1)


def exact_repeats(lines: DataFrame) -> DataFrame:
    """First place of every distinct line that occurs more than once: (a, b, first)."""
    place = F.struct("doc_id", "mark", "pos")
    return lines.groupBy("a", "b").agg(F.count("*").alias("n"), F.min(place).alias("first")).where("n > 1").select("a", "b", "first")


_BASE = np.uint64(0x9E3779B97F4A7C15)
_UNBASE = np.uint64(pow(int(_BASE), -1, 2**64))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def deletions(part: np.ndarray) -> tuple[np.ndarray, np.uint64]:
    """Hashes of all deletions of one code point, and of the part itself: sums of powers, shifted behind the deleted place."""
    powers = np.cumprod(np.concatenate([[np.uint64(1)], np.full(max(0, len(part) - 1), _BASE)]).astype(np.uint64))
    terms = _mixed(part.astype(np.uint64) + np.uint64(1)) * powers[: len(part)]
    upto = np.cumsum(terms, dtype=np.uint64)
    whole = upto[-1] if len(part) else np.uint64(0)
    return (upto - terms) + (whole - upto) * _UNBASE, whole


def _variants(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Keys of lines that share a half: (a, b, k, place), place 0 for a line in the role of the shorter partner.

    Half keys in order: own length (first half whole, second half whole), length + 1 (the same).
    """
    for whole in batches:
        for a, b, key, which, line in zip(*(whole.column(c).to_pylist() for c in ("a", "b", "key", "which", "line"))):
            points = np.frombuffer(line.encode("utf-32-le"), "<u4")
            length = len(points) + (which >= 2)
            half = length // 2
            offset, part = (half, points[half:]) if which % 2 == 0 else (0, points[: len(points) - (length - half)])
            each, own = deletions(part)
            if which < 2:
                found, places = each, np.arange(offset + 1, offset + len(part) + 1, dtype=np.int32)
            else:
                found, places = np.array([own], np.uint64), np.zeros(1, np.int32)
            k = _mixed(found + np.uint64(key % 2**64)).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), a)), pa.array(np.full(len(k), b)), pa.array(k), pa.array(places)], names=["a", "b", "k", "place"])


def _merged(batches: Iterator[pa.RecordBatch], rows: int = 20_000) -> Iterator[pa.RecordBatch]:
    """Small batches put together."""
    held: list[pa.RecordBatch] = []
    n = 0
    for b in _variants(batches):
        held.append(b)
        n += b.num_rows
        if n >= rows:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
            held, n = [], 0
    if held:
        yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def near_repeats(docs: DataFrame, min_chars: int = MIN_CHARS, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Distinct lines (a, b) that have an earlier line within one edit."""
    keyed = _lines(docs).withColumn("n", F.length("line")).where(F.col("n") >= min_chars).withColumn("id", F.xxhash64("line"))
    halves = keyed.select("id", F.explode(F.array(*_half_keys(F.col("line"), F.col("n")))).alias("key"))
    shared = halves.groupBy("key").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo <> hi").select("key")
    shared = persist_table(shared, "lines-halves")
    few = shared.count() <= broadcast_rows
    hint = (lambda df: F.broadcast(df)) if few else (lambda df: df)
    # Lines of shared halves, once each, with their first place
    whole = keyed.select("doc_id", "mark", "pos", "line", _hash(F.col("line")).alias("h"), F.posexplode(F.array(*_half_keys(F.col("line"), F.col("n")))).alias("which", "key"))
    hits = whole.join(hint(shared), "key", "left_semi").select("h.a", "h.b", "line", "which", "key", F.struct("doc_id", "mark", "pos").alias("at"))
    hits = persist_table(hits.groupBy("a", "b", "line", "which", "key").agg(F.min("at").alias("at")), "lines-hits")
    keys = hits.select("a", "b", "key", "which", "line").mapInArrow(_merged, "a long, b long, k long, place int")
    keys = persist_table(keys, "lines-keys")
    agreed = keys.groupBy("k").agg(F.min("a").alias("lo"), F.max("a").alias("hi")).where("lo <> hi").select("k")
    # Only lines that agree in a variant meet, as hashes; their texts come in for the pairs that are left
    texts = hits.groupBy("a", "b").agg(F.min("at").alias("at"), F.first("line").alias("line"))
    places = texts.select("a", "b", "at")
    met = persist_table(keys.join(agreed, "k").join(places, ["a", "b"]).select("k", "place", F.struct("a", "b").alias("h"), "at"), "lines-met")
    earliest = F.min(F.struct("at", "h")).alias("f")
    # substitution: lines of one length that agree with the same place deleted
    first = met.where("place > 0").groupBy("k", "place").agg(earliest)
    subs = met.where("place > 0").join(first, ["k", "place"]).where("f.h <> h").select("h", "at", "f", "place", F.lit(True).alias("same_length"))
    # insertion or deletion: the later of the longer and the shorter line goes
    short = met.where("place = 0").groupBy("k").agg(earliest)
    pairs = met.where("place > 0").join(short, "k").where("f.h <> h").select("h", "at", "f", "place", F.lit(False))
    pairs = subs.union(pairs).groupBy("h", "at", "f", "same_length").agg(F.min("place").alias("p"))
    one = texts.select(F.struct("a", "b").alias("h"), F.col("line").alias("x"))
    two = texts.select(F.struct("a", "b").alias("o"), F.col("line").alias("y"))
    full = pairs.withColumn("o", F.col("f.h")).join(one, "h").join(two, "o")
    before = F.expr("substring(x, 1, p - 1)")
    after = F.expr("substring(x, p + 1, length(x))")
    as_other = F.when(F.col("same_length"), F.concat(before, F.expr("substring(y, p, 1)"), after)).otherwise(F.concat(before, after))
    gone = full.where(as_other == F.col("y")).select(F.when(F.col("f.at") < F.col("at"), F.col("h")).otherwise(F.col("o")).alias("h"))
    return gone.distinct().select("h.a", "h.b")


def removed_lines(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc_id, mark, gone, n_exact, n_near): positions to remove, for each document with any."""
    docs = docs.select("doc_id", "text")
    lines = persist_table(_lines(docs).select("doc_id", "mark", "pos", _hash(F.col("line")).alias("h")).select("doc_id", "mark", "pos", "h.a", "h.b"), "lines")
    near = persist_table(near_repeats(docs, min_chars), "lines-near")
    first = exact_repeats(lines).withColumn("near", F.lit(False)).union(near.select("a", "b", F.lit(None).cast(dict(exact_repeats(lines).dtypes)["first"]), F.lit(True)))
    marks = persist_table(first.groupBy("a", "b").agg(F.max("first").alias("first"), F.max("near").alias("near")), "lines-marks")
    hit = lines.join(marks, ["a", "b"]).where("near or not (doc_id <=> first.doc_id and mark = first.mark and pos = first.pos)")
    gone = hit.groupBy("doc_id", "mark").agg(F.collect_set("pos").alias("gone"), F.count_if("near").alias("n_near"), F.count_if(~F.col("near")).alias("n_exact"))
    return persist_table(gone, "lines-gone")


def dedup(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """``docs`` with repeated lines taken out of ``text``; adds ``removed`` and ``removed_near``, numbers of lines."""
    gone = removed_lines(docs, min_chars).select(F.col("doc_id").alias("__id"), F.col("mark").alias("__m"), "gone", "n_exact", "n_near")
    left = docs.withColumn("__mark", F.xxhash64("text")).alias("d")
    full = left.join(gone, (F.col("__mark") == F.col("__m")) & F.col("d.doc_id").eqNullSafe(F.col("__id")), "left")
    kept = F.filter(F.split("d.text", "\n", -1), lambda _, i: ~F.array_contains("gone", i))
    text = F.when(F.col("gone").isNull() | F.col("d.text").isNull(), F.col("d.text")).otherwise(F.array_join(kept, "\n"))
    columns = [text.alias("text") if c == "text" else F.col(f"d.`{c}`") for c in docs.columns if c not in ("removed", "removed_near")]
    return full.select(*columns, (F.coalesce("n_exact", F.lit(0)) + F.coalesce("n_near", F.lit(0))).alias("removed"), F.coalesce("n_near", F.lit(0)).alias("removed_near"))


def op3_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = dedup(table(spark, sf_dir, "documents", "doc_id", "text"))
    return done.select("doc_id", "removed", "removed_near", F.length("text").cast("long").alias("n_chars"), F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))
