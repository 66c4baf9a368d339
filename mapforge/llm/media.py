"""Operator 6: media columns over content-addressed payloads in tar shards.

Each task writes one tar shard into the shared folder: a member per distinct payload, named by its
digest. The index table carries digest, shard, offset and length. Metadata columns come from range
reads of the first bytes of a member; payload features from a range read of the whole member. Copies
met by one task share a member; the index keeps one place for each digest, so copies in the shards
of other tasks are never referenced. A shard gets a new name with each attempt, and only shards of
attempts that succeeded enter the index; what failed or superseded attempts left is removed once the
index is written.

The stored form is an 8-bit greyscale PNG of ``WIDTH`` columns: lossless, with its metadata in the
first 33 bytes. Null text counts as empty. Equal texts give equal values, repeated rows included; a very long text
is a tall image. An empty table gives no shard and no rows.
"""

from __future__ import annotations

import hashlib
import io
import struct
import tarfile
import uuid
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from mapforge.llm.common import fresh_path, persist_table, table

WIDTH = 576
HEADER_BYTES = 33
SLICE_ROWS = 256
_SIGNATURE = b"\x89PNG\r\n\x1a\n"


def payload_of(text: str | None) -> bytes:
    """UTF-8 bytes of a text, padded with bytes 255 to a positive multiple of ``WIDTH``."""
    raw = (text or "").encode()
    return raw + b"\xff" * (max(WIDTH, -(-len(raw) // WIDTH) * WIDTH) - len(raw))


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(body, zlib.crc32(kind)))


def to_png(payload: bytes) -> bytes:
    """Greyscale PNG whose rows, each unfiltered, are the payload."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    lines = np.zeros((len(rows), WIDTH + 1), np.uint8)
    lines[:, 1:] = rows
    head = struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)
    return _SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), 6)) + _chunk(b"IEND", b"")


def read_header(first: bytes) -> tuple[int, int, int, int]:
    """width, height, bit depth and colour type from the first bytes of a PNG."""
    if first[:8] != _SIGNATURE or first[12:16] != b"IHDR":
        raise ValueError("not a PNG header")
    return struct.unpack(">IIBB", first[16:26])


def from_png(data: bytes) -> bytes:
    """Samples of a PNG made by :func:`to_png`."""
    width, height, depth, colour = read_header(data)
    if (depth, colour) != (8, 0):
        raise ValueError("only 8-bit greyscale is stored here")
    at, body = 8, []
    while at < len(data):
        (size,) = struct.unpack(">I", data[at : at + 4])
        if data[at + 4 : at + 8] == b"IDAT":
            body.append(data[at + 8 : at + 8 + size])
        at += 12 + size
    lines = np.frombuffer(zlib.decompress(b"".join(body)), np.uint8).reshape(height, width + 1)
    if lines[:, 0].any():
        raise ValueError("filtered rows are not stored here")
    return lines[:, 1:].tobytes()


def write_shards(docs: DataFrame, key: str = "doc_id", text: str = "text", folder: str | None = None) -> DataFrame:
    """Store payloads in tar shards; one row per document: key, digest, shard, offset, length, n_bytes."""
    spark = docs.sparkSession
    folder = folder or fresh_path(spark, "media")
    schema = docs.select(F.col(key).alias("key")).schema.add("digest", "binary").add("shard", "string").add("offset", "long").add("length", "long").add("n_bytes", "long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = fs.FileSystem.from_uri(folder)
        store.create_dir(root, recursive=True)
        shard, out, at, known = f"{uuid.uuid4().hex}.tar", None, 0, {}
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part, rows = whole.slice(i, SLICE_ROWS), []
                for k, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    payload = payload_of(t)
                    size = len((t or "").encode())
                    name = hashlib.sha256(b"%d:" % size + payload).digest()
                    if name not in known:
                        data = to_png(payload)
                        info = tarfile.TarInfo(name.hex()[:60])
                        info.size = len(data)
                        member = info.tobuf(tarfile.USTAR_FORMAT) + data + bytes(-len(data) % tarfile.BLOCKSIZE)
                        out = out or store.open_output_stream(f"{root}/{shard}")
                        out.write(member)
                        known[name] = (at + tarfile.BLOCKSIZE, len(data))
                        at += len(member)
                    rows.append((k, name, f"{folder}/{shard}", *known[name], size))
                if rows:
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(c, kind) for c, kind in zip(zip(*rows), [part.column(0).type, pa.binary(), pa.string(), pa.int64(), pa.int64(), pa.int64()])],
                        names=["key", "digest", "shard", "offset", "length", "n_bytes"],
                    )
        if out:
            out.write(bytes(2 * tarfile.BLOCKSIZE))
            out.close()

    rows = persist_table(docs.select(F.col(key).alias("key"), text).mapInArrow(run, schema), "media-rows")
    sweep(folder, {r["shard"] for r in rows.select("shard").distinct().collect()})  # a name for each task
    return rows


def sweep(folder: str, used: set[str]) -> list[str]:
    """Remove shards that no index row names: those of attempts that failed or that another attempt superseded."""
    store, root = fs.FileSystem.from_uri(folder)
    listed = store.get_file_info(fs.FileSelector(root, allow_not_found=True))
    names = {f.rsplit("/", 1)[1] for f in used}
    gone = [f.path for f in listed if f.base_name.endswith(".tar") and f.base_name not in names]
    for path in gone:
        store.delete_file(path)
    return gone


def index(rows: DataFrame) -> DataFrame:
    """One place for each digest."""
    place = F.min(F.struct("shard", "offset", "length", "n_bytes")).alias("p")
    return rows.groupBy("digest").agg(place).select("digest", "p.*")


def header_columns(places: DataFrame) -> DataFrame:
    """``places`` with width, height, depth and colour, from range reads of headers alone."""
    return _ranges(places, "width long, height long, depth long, colour long", lambda f, r: read_header(_read(f, r["offset"], HEADER_BYTES)))


def payload_columns(places: DataFrame) -> DataFrame:
    """``places`` with what the stored bytes themselves show."""

    def look(f, r: dict) -> tuple:
        data = _read(f, r["offset"], r["length"])
        got = from_png(data)
        seen = np.bincount(np.frombuffer(got, np.uint8), minlength=256)
        share = seen[seen > 0] / len(got)
        feature = f"mean={np.dot(seen, np.arange(256)) / len(got):.4f} entropy={abs(-(share * np.log2(share)).sum()):.4f} levels={len(share)}"
        return len(got), hashlib.sha256(got).hexdigest(), zlib.crc32(got[-32:]), len(data), hashlib.sha256(data).hexdigest(), feature

    return _ranges(places, "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string", look)


def _read(f, offset: int, length: int) -> bytes:
    f.seek(offset)
    return f.read(length)


def _ranges(places: DataFrame, columns: str, look) -> DataFrame:
    schema = StructType(list(places.schema.fields))
    for c in columns.split(", "):
        schema = schema.add(*c.split(" "))
    extra = [c.split(" ")[0] for c in columns.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                rows, got = part.to_pylist(), {}
                by_shard: dict[str, list[int]] = defaultdict(list)
                for n, r in enumerate(rows):
                    by_shard[r["shard"]].append(n)
                for shard, members in by_shard.items():
                    store, path = fs.FileSystem.from_uri(shard)
                    with store.open_input_file(path) as f:
                        for n in sorted(members, key=lambda n: rows[n]["offset"]):
                            got[n] = look(f, rows[n])
                cols = list(zip(*(got[n] for n in range(len(rows)))))
                yield pa.RecordBatch.from_arrays([*part.columns, *(pa.array(c) for c in cols)], names=[*part.schema.names, *extra])

    return places.mapInArrow(run, schema)


def members(shard: bytes) -> list[tuple[str, int, int]]:
    """Name, offset and length of each member, by the tar format itself (for checks of a shard)."""
    with tarfile.open(fileobj=io.BytesIO(shard)) as t:
        return [(m.name, m.offset_data, m.size) for m in t.getmembers()]


def op6_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = write_shards(table(spark, sf_dir, "documents", "doc_id", "text"))
    # Sorted by place, neighbouring index rows read neighbouring bytes of one shard; as many tasks read as wrote.
    shards = max(1, rows.select("shard").distinct().count())
    places = index(rows).repartitionByRange(shards, "shard", "offset").sortWithinPartitions("shard", "offset")
    # Headers first, by ranges of HEADER_BYTES alone, then whole members
    seen = payload_columns(header_columns(places)).withColumn("feature", F.format_string("png %dx%dx%d colour=%d %s", "width", "height", "depth", "colour", "feature"))
    # Digests wait as bytes, half as long as their digits
    sums = ("payload_sha256", "media_sha256")
    seen = seen.withColumns({c: F.unhex(c) for c in sums}).select("digest", "width", "height", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")
    full = rows.select(F.col("key").alias("doc_id"), "digest", "n_bytes").join(persist_table(seen, "media-seen"), "digest").withColumns({c: F.lower(F.hex(c)) for c in sums})
    return full.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "width", "height")
