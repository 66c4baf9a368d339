"""Operator 8: BPE encoding and decoding over a table of distinct words.

1. Texts are cut into words. Documents go in blocks; a block numbers its distinct words, and its documents are
   written to a file of the shared folder with word numbers in place of words. The words of a block become one row
   for each bucket of the corpus-wide word table that they fall into.
2. The word table is dealt by bucket; a task that holds a bucket sees each of its words in every block that has it,
   encodes each distinct word once and hands its ids back to the blocks.
3. Ids are dealt by block; a task reads the block's documents from their place and gathers each document's ids by
   word number, that is, by position.

So what is shuffled is words per block and their ids, neither texts nor a row per word position, and a task holds the words
of one bucket or of one block. Decoding gathers pieces by id through the id-to-piece table, whose size is the
vocabulary's and so does not grow with the corpus.

Results are those of the tokenizers library for ``encode(text, add_special_tokens=False)`` and
``decode(ids, skip_special_tokens=False)``. Words are cut by the rules of the lower-casing word vocabulary named
below; vocabulary files with other rules are refused. Null text counts as empty; an empty text has no ids; rows that
repeat are encoded alike; an empty table gives no rows. Columns other than the text stay, whatever their names.
"""

from __future__ import annotations

import json
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator
from functools import lru_cache
from struct import pack
from uuid import uuid4

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import fresh_path, persist_table, table

VOCABULARY = "word_bpe_49k.json"
#: A block of documents is closed once it has this many distinct words or word positions.
BLOCK_WORDS = 100_000
BLOCK_POSITIONS = 1_500_000
#: Bytes of input for each bucket of the word table.
BUCKET_BYTES = 12_000_000
#: Parts of words, as a word and the marks behind it, that a task keeps from pack to pack; more are forgotten, which changes no result.
PIECES = 50_000
#: How hard words, numbers and ids are compressed before they are written.
LEVEL = 6
#: Bytes of words and ids that a generation of a task's own table (see ``WordTable``) may hold.
TABLE_BYTES = 32_000_000
SLICE_ROWS = 256

# Texts of these characters only are cut by the pattern below, which for them equals the library's
# own normaliser and splitter; all other texts go through the library's.
_PLAIN = re.compile("[^\t\n\x0b\x0c\r -~À-ÖØ-öø-ÿ]")
_WORDS = re.compile("[a-zß-öø-ÿ]+|[0-9]|'(?:s|t|re|ve|m|ll|d)|[^\\sa-z0-9ß-öø-ÿ]+")
#: The rules that a vocabulary file must have for the above to hold.
_RULES = {
    "normalizer": ["NFC", "Replace", "Lowercase"],
    "pre_tokenizer": ["Split", "ByteLevel"],
    "split": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+",
}


def vocabulary_path(name_or_path: str = VOCABULARY) -> str:
    """Place of a public vocabulary file, or the given path itself."""
    if "/" in name_or_path:
        return name_or_path
    import public_tokenizers

    return str(public_tokenizers.path(name_or_path))


def _byte_letters() -> list[str]:
    """The letter that stands for each byte in the vocabulary: printable bytes stand for themselves, the rest follow from 256."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(rest)) for b in range(256)]


def _refuse_other_rules(spec: dict) -> None:
    steps = lambda key, inner: [x["type"] for x in (spec.get(key) or {}).get(inner, [])]
    cut = (spec.get("pre_tokenizer") or {}).get("pretokenizers", [{}])[0].get("pattern", {}).get("Regex")
    plain = all(not t[k] for t in spec["added_tokens"] for k in ("single_word", "lstrip", "rstrip", "normalized"))
    same = steps("normalizer", "normalizers") == _RULES["normalizer"] and steps("pre_tokenizer", "pretokenizers") == _RULES["pre_tokenizer"] and cut == _RULES["split"]
    if not same or not plain or spec.get("decoder") is not None or spec["model"]["type"] != "BPE":
        raise ValueError("this vocabulary cuts words by other rules")


class Vocabulary:
    """A vocabulary file: cuts texts into words, encodes a word, names the piece of an id."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        _refuse_other_rules(spec)
        self.tokenizer = Tokenizer.from_str(json.dumps(spec))
        self.tokenize = self.tokenizer.model.tokenize
        self.letters = _byte_letters()
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.split = re.compile("(" + "|".join(map(re.escape, self.specials)) + ")")
        named = self.tokenizer.get_vocab(with_added_tokens=True)
        pieces = [""] * (max(named.values()) + 1)
        for piece, k in named.items():
            pieces[k] = piece
        self.pieces = pa.array(pieces, pa.large_string())

    def _cut(self, text: str) -> list[str]:
        if not _PLAIN.search(text):
            return text.lower().split()
        norm = self.tokenizer.normalizer.normalize_str(text)
        return [norm[a:b] for _, (a, b) in self.tokenizer.pre_tokenizer.pre_tokenize_str(norm)]

    def cut(self, text: str | None) -> list[str]:
        """Normalised words of a text, special tokens with a space before them: no token crosses from one into the next."""
        if not text:
            return []
        parts = self.split.split(text)
        if len(parts) == 1:
            return self._cut(text)
        return [w for part in parts if part for w in ([f" {part}"] if part in self.specials else self._cut(part))]

    def parts(self, word: str) -> list[str]:
        """The words of which a word between white space is made."""
        if word[0] == " " or (word.isascii() and word.isalpha()):
            return [word]
        return [word] if _PLAIN.search(word) else _WORDS.findall(word)

    def part_ids(self, part: str) -> bytes:
        """Ids of one part as little-endian unsigned 32-bit integers."""
        if part[0] == " ":
            return np.array([self.specials[part[1:]]], "<u4").tobytes()
        # Letters, digits and marks of ASCII stand for themselves; no part holds white space or control characters among them
        piece = part if part.isascii() and part.isprintable() else "".join([self.letters[b] for b in part.encode()])
        ids = [t.id for t in self.tokenize(piece)]
        return pack(f"<{len(ids)}I", *ids)


@lru_cache(maxsize=1)
def vocabulary_of(path: str) -> Vocabulary:
    return Vocabulary(path)


class WordTable:
    """The words that one task has met lately, with their ids: two generations of ``TABLE_BYTES`` at most.

    When the younger is full it becomes the older, and the older goes; a word that is met again moves back. So
    frequent words stay, memory is bounded (but for the words of one text), and no result changes.
    """

    def __init__(self, path: str):
        self.vocabulary, self.held = vocabulary_of(path), 0
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def learn(self, words: set[str]) -> None:
        """Enter words that the younger generation lacks; the parts of which they are made enter it too."""
        known, older, part_ids, parts_of = self.known, self.older, self.vocabulary.part_ids, self.vocabulary.parts
        before = len(known)
        for w in words:
            found = older.get(w)
            if found is None:
                parts = parts_of(w)
                if len(parts) == 1:
                    found = part_ids(w)
                else:
                    each = []
                    for p in parts:
                        x = known.get(p)
                        if x is None:
                            x = known[p] = older.get(p) or part_ids(p)
                        each.append(x)
                    found = b"".join(each)
            known[w] = found
            self.held += 2 * (len(w) + len(found))
        self.held += 200 * (len(known) - before)  # what Python keeps beside them

    def of(self, words: list[str]) -> list[bytes]:
        if self.held > TABLE_BYTES:
            self.known, self.older, self.held = {}, self.known, 0
        known = self.known
        self.learn({w for w in words if w not in known})
        return [known[w] for w in words]

    def encode(self, text: str | None) -> bytes:
        words, known = self.vocabulary.cut(text), self.known
        try:
            return b"".join([known[w] for w in words])
        except KeyError:
            return b"".join(self.of(words))


def _packed(batch: pa.RecordBatch) -> bytes:
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(batch)
    return out.getvalue().to_pybytes()


def _unpacked(payload: bytes) -> pa.RecordBatch:
    return pa.ipc.open_stream(payload).read_next_batch()


def _buckets(docs: DataFrame) -> int:
    """Buckets of the word table by the size of the input files, by the number of rows where that is not known."""
    size = int(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    n = size // BUCKET_BYTES if size < 2**50 else docs.count() // 4000
    return int(max(8, min(16_384, n)))


#: A block's words of one bucket, or their ids: where the block's documents are, the bucket, and the packed words or ids.
_ROW = "file string, at long, size long, bucket int, payload binary"
_KINDS = (pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.binary())


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _KINDS)], names=[x.split(" ")[0] for x in _ROW.split(", ")])


def _to_blocks(path: str, folder: str, keep: list[str], text: str, buckets: int):
    """Step 1: documents of each block to the task's file, words of each block by bucket out (bucket 0 always)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, name, out, at = vocabulary_of(path), f"{uuid4().hex}.blocks", None, 0
        store, root = fs.FileSystem.from_uri(folder)

        def fresh() -> defaultdict:
            numbers: defaultdict = defaultdict()
            numbers.default_factory = numbers.__len__
            return numbers

        def closed(numbers: dict[str, int], docs: list[tuple[pa.RecordBatch, list[list[int]]]]) -> Iterator[pa.RecordBatch]:
            nonlocal out, at
            words = list(numbers)
            home = [zlib.crc32(w.encode()) % buckets for w in words]
            # Numbers in the order of buckets and words: the packs then need not carry them
            order = sorted(range(len(words)), key=lambda k: (home[k], words[k]))
            rank = np.empty(len(words), "u4")
            rank[order] = np.arange(len(words), dtype="u4")
            body = []
            for part, found in docs:
                ends = np.concatenate([[0], np.cumsum([len(x) for x in found])])
                flat = rank[np.fromiter((n for x in found for n in x), np.int64, int(ends[-1]))]
                batch = pa.RecordBatch.from_arrays([*part.columns, pa.array(np.diff(ends))], names=[str(k) for k in range(len(part.columns) + 1)])
                # Numbers by their bytes: the first bytes of all, then the second, then the third
                planes = np.ascontiguousarray(flat.astype("<u4").view("u1").reshape(-1, 4).T)
                for x in (_packed(batch), zstandard.compress(planes.tobytes(), LEVEL)):
                    body += [len(x).to_bytes(8, "little"), x]
            body = b"".join(body)
            if out is None:
                store.create_dir(root, recursive=True)
                out = store.open_output_stream(f"{root}/{name}")
            out.write(body)
            place = (f"{folder}/{name}", at, len(body))
            at += len(body)
            by_bucket: dict[int, list[str]] = {0: []}
            for k in order:
                by_bucket.setdefault(home[k], []).append(words[k])
            for b, own in by_bucket.items():
                yield _rows([(*place, b, zstandard.compress("\n".join(own).encode(), LEVEL))])

        numbers, docs, positions = fresh(), [], 0
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                found = [[numbers[w] for w in vocabulary.cut(t)] for t in part.column(text).to_pylist()]
                docs.append((part.select(keep), found))
                positions += sum(map(len, found))
                if len(numbers) >= BLOCK_WORDS or positions >= BLOCK_POSITIONS:
                    yield from closed(numbers, docs)
                    numbers, docs, positions = fresh(), [], 0
        if docs:
            yield from closed(numbers, docs)
        if out is not None:
            out.close()

    return run


def _encode_words(path: str):
    """Step 2: words in the order of their buckets in, ids out; each distinct word of a bucket is encoded once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, last, known, pieces = vocabulary_of(path), None, {}, {}
        for whole in batches:
            for *place, bucket, payload in zip(*(c.to_pylist() for c in whole.columns)):
                if bucket != last:
                    last, known = bucket, {}
                words = zstandard.decompress(payload).decode()
                words = words.split("\n") if words else []
                if len(pieces) > PIECES:
                    pieces.clear()
                for w in words:
                    if w in known:
                        continue
                    parts = vocabulary.parts(w)
                    if len(parts) == 1:
                        known[w] = vocabulary.part_ids(w)
                        continue
                    for p in parts:
                        if p not in pieces:
                            pieces[p] = vocabulary.part_ids(p)
                    known[w] = b"".join([pieces[p] for p in parts])
                ids = [known[w] for w in words]
                sizes = np.array([len(x) // 4 for x in ids], "<u4")
                yield _rows([(*place, bucket, zstandard.compress(len(ids).to_bytes(8, "little") + sizes.tobytes() + b"".join(ids), LEVEL))])

    return run


def _to_documents(keep: list[str]):
    """Step 3: ids of words in the order of blocks and buckets in; documents with their ids out."""

    def documents(place: tuple[str, int, int], packs: list[bytes]) -> Iterator[pa.RecordBatch]:
        sizes, parts = [], []
        for p in map(zstandard.decompress, packs):
            n = int.from_bytes(p[:8], "little")
            sizes.append(np.frombuffer(p, "<u4", n, 8))
            parts.append(np.frombuffer(p, "<u4", -1, 8 + 4 * n) if len(p) > 8 + 4 * n else np.empty(0, "<u4"))
        size, data = np.concatenate(sizes).astype(np.int64), np.concatenate(parts)
        begin = np.cumsum(size) - size
        file, at, length = place
        store, path = fs.FileSystem.from_uri(file)
        with store.open_input_file(path) as f:
            f.seek(at)
            body = f.read(length)
        k = 0
        while k < length:
            both = []
            for _ in range(2):
                n = int.from_bytes(body[k : k + 8], "little")
                both.append(body[k + 8 : k + 8 + n])
                k += 8 + n
            pack = _unpacked(both[0])
            counts = pack.column(pack.num_columns - 1).to_numpy()
            planes = np.frombuffer(zstandard.decompress(both[1]) if counts.any() else b"", np.uint8).reshape(4, -1)
            where = np.ascontiguousarray(planes.T).view("<u4").ravel().astype(np.int64)
            each = size[where] if len(where) else np.empty(0, np.int64)
            total = np.concatenate([[0], np.cumsum(each)])
            ids = data[np.repeat(begin[where] - total[:-1], each) + np.arange(total[-1])] if len(where) else data[:0]
            bounds = (4 * total[np.concatenate([[0], np.cumsum(counts)])]).astype("<i8")
            out = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(counts), [None, pa.py_buffer(bounds.tobytes()), pa.py_buffer(ids.astype("<u4").tobytes())])
            yield pa.RecordBatch.from_arrays([*(pack.column(c) for c in range(len(keep))), out.cast(pa.binary())], names=[*keep, "ids"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, packs = None, []
        for whole in batches:
            for *place, _, payload in zip(*(c.to_pylist() for c in whole.columns)):
                if place != last:
                    if last:
                        yield from documents(last, packs)
                    last, packs = place, []
                packs.append(payload)
        if last:
            yield from documents(last, packs)

    return run


def encode(docs: DataFrame, text: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """``docs`` without its text column and with ``ids``, the token ids as little-endian unsigned 32-bit binary."""
    path = vocabulary_path(vocabulary)
    keep = [c for c in docs.columns if c not in (text, "ids")]
    schema = docs.select(*keep, F.lit(b"").alias("ids")).schema
    docs = docs.select(*keep, text)
    buckets = _buckets(docs)
    blocks = persist_table(docs.mapInArrow(_to_blocks(path, fresh_path(docs.sparkSession, "bpe-documents"), keep, text, buckets), _ROW), "bpe-words")
    # twice as many ranges as buckets: then hardly two buckets share one
    words = blocks.repartitionByRange(2 * buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(_encode_words(path), _ROW)
    return words.repartition(buckets, "file", "at").sortWithinPartitions("file", "at", "bucket").mapInArrow(_to_documents(keep), schema)


def decode(encoded: DataFrame, ids: str = "ids", vocabulary: str = VOCABULARY) -> DataFrame:
    """``encoded`` with ``decoded``, the pieces of its ids taken from the id-to-piece table."""
    path = vocabulary_path(vocabulary)
    keep = [c for c in encoded.columns if c != "decoded"]
    schema = encoded.select(*keep, F.lit("").alias("decoded")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = vocabulary_of(path).pieces
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                each = [x or b"" for x in part.column(ids).to_pylist()]
                ends = np.concatenate([[0], np.cumsum([len(x) // 4 for x in each])])
                taken = pieces.take(pa.array(np.frombuffer(b"".join(each), "<u4")))
                texts = pc.binary_join(pa.ListArray.from_arrays(pa.array(ends, pa.int32()), taken), pa.scalar(" ", pa.large_string()))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), texts.cast(pa.string())], names=[*keep, "decoded"])

    return encoded.select(*keep).mapInArrow(run, schema)


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return decode(encode(docs)).select(
        "doc_id",
        (F.length("ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )
