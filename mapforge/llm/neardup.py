"""Operator 7: n-gram Jaccard join through a MinHash LSH forest.

Texts become sets of hashed runs of five words (lower case; shorter texts with any word: one run of
all of them). Equal sets form one class. A class has a label of ``DEPTH`` minhashes in each of
``TREES`` prefix trees, kept as a sortable string of two bytes a minhash, so that the sets below a node
of a tree are those whose labels share a prefix. The matched prefix starts at the full depth and is shortened until
two things hold: pairs at the threshold meet below some node with probability ``RECALL`` or more, and so
did the share ``RECALL`` of the links of ``QUERIES`` sampled sets, each compared exactly with every set of
the input. Below the nodes of that depth every pair is verified exactly.

No pair is ever a row: the sets below a node are cut into blocks of at most ``BLOCK`` sets, a task counts a pair
of blocks by matrix products and returns, for each set, its number of links and one root of those
it is linked to there. Nodes with the same sets are verified once, and a pair that meets below
several nodes counts only in the first of their trees, so all link counts are exact for the pairs met. Counting the
links of a node with N sets exactly takes N / BLOCK copies of each set in the shuffle.

Null and empty texts have no set and link with nothing. Rows that repeat a text share its class. A class
is named by its least doc_id; rows with a null doc_id link as others do and name a class only where
no other row is in it. Very long texts are cut and hashed whole; an empty table gives no rows.
"""

from __future__ import annotations

import pickle
import re
from collections.abc import Iterator
from functools import lru_cache
from hashlib import blake2b

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import connected_components, persist_table, small_batches, table

WORDS = 5
THRESHOLD = 0.8
TREES = 20
DEPTH = 8
RECALL = 0.999
QUERIES = 500
QUERY_RUNS = 200_000
BLOCK = 256
SLICE_ROWS = 256
#: Bytes of a minhash in a label.
STEP = 2
#: Words whose hashes a task keeps, of 40 letters at most: some 10 MB. A full table is emptied, which changes no result.
KNOWN_WORDS = 60_000
_WORD = re.compile(r"\w+")
_SEEN = np.uint64(42)


def meeting_chance(jaccard: float, prefix: int, trees: int = TREES) -> float:
    """Probability that two sets of this similarity share a prefix in at least one tree."""
    return 1 - (1 - jaccard**prefix) ** trees


def prefix_length(threshold: float = THRESHOLD, trees: int = TREES, depth: int = DEPTH, recall: float = RECALL, met: list[int] | None = None) -> int:
    """Shorten the prefix from the full depth until pairs at the threshold meet often enough.

    ``met[k]``: how many sampled links share a prefix of exactly ``k`` at best, in their best tree.
    """
    links = sum(met or [])
    for prefix in range(depth, 1, -1):
        seen = not links or sum(met[prefix:]) >= recall * links
        if seen and meeting_chance(threshold, prefix, trees) >= recall:
            return prefix
    return 1


class Words:
    """Hashes of words; a task keeps those it has met, up to a bound."""

    def __init__(self) -> None:
        self.known: dict[str, int] = {}

    def code(self, word: str) -> int:
        code = xxhash.xxh3_64_intdigest(word) | 1
        if len(word) <= 40:
            if len(self.known) >= KNOWN_WORDS:
                self.known.clear()
            self.known[word] = code
        return code


def shingles(text: str | None, words: int = WORDS, table_: Words | None = None) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's word runs."""
    found = _WORD.findall(text.lower()) if text else []
    if not found:
        return np.empty(0, np.uint64)
    own = table_ or Words()
    get, code = own.known.get, own.code
    codes = np.array([get(w) or code(w) for w in found], np.uint64)
    n = min(words, len(codes))
    mixed = np.zeros(len(codes) - n + 1, np.uint64)
    for k in range(n):
        mixed = (mixed ^ codes[k : len(codes) - n + 1 + k]) * np.uint64(0x9E3779B97F4A7C15)
        mixed ^= mixed >> np.uint64(29)
    return np.unique(mixed)


@lru_cache(maxsize=4)
def _coefficients(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(7)
    return rng.integers(1, 2**32, count, np.uint32) | np.uint32(1), rng.integers(0, 2**32, count, np.uint32)


def labels(hashes: np.ndarray, trees: int = TREES, depth: int = DEPTH) -> np.ndarray:
    """The set's label in each tree: ``depth`` minhashes of two bytes."""
    a, b = _coefficients(trees * depth)
    low = np.full(trees * depth, np.iinfo(np.uint32).max, np.uint32)
    upper = (hashes >> np.uint64(32)).astype(np.uint32)
    for i in range(0, len(upper), 512):  # products that fit the cache
        low = np.minimum(low, (upper[i : i + 512, None] * a + b).min(axis=0))
    return (low & np.uint32(0xFFFF)).astype(">u2").reshape(trees, depth)


def common_prefix(a: np.ndarray, b: np.ndarray) -> int:
    """The longest prefix that two sets' labels share in any tree."""
    same = a == b
    return int(np.cumprod(same, axis=1).sum(1).max())


def _name(hashes: np.ndarray) -> bytes:
    return blake2b(hashes.tobytes(), digest_size=16).digest()


def _sampled(docs: DataFrame, queries: int, runs: int) -> dict:
    """Sets of at most ``queries`` texts, of at most ``runs`` runs together, in the order of a hash of the texts, indexed by run."""
    keys = docs.select(F.xxhash64("text").alias("mark")).where("text is not null").distinct().orderBy(F.xxhash64(F.lit(17), "mark")).limit(queries)
    texts = docs.select(F.xxhash64("text").alias("mark"), "text").join(F.broadcast(keys), "mark").groupBy("mark").agg(F.first("text").alias("text"))
    sets: list[np.ndarray] = []
    total = 0
    for r in texts.orderBy(F.xxhash64(F.lit(17), "mark")).select("text").toLocalIterator():
        s = shingles(r["text"])
        if total + len(s) > runs:
            continue
        total += len(s)
        if len(s):
            sets.append(s)
    sets = list({_name(s): s for s in sets}.values())
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    every = np.concatenate(sets) if sets else np.empty(0, np.uint64)
    order = np.argsort(every, kind="stable")
    return {"runs": every[order], "owner": owner[order], "size": np.array([len(s) for s in sets]), "labels": [labels(s) for s in sets]}


def _links_of_sample(sample: dict, hashes: np.ndarray, own: np.ndarray, threshold: float) -> list[int]:
    """For each sampled set that this one links with, itself excepted, the longest prefix they share."""
    if not len(sample["runs"]):
        return []
    few = hashes[sample["seen"][hashes >> _SEEN]]  # nearly all runs end at this table
    lo, hi = np.searchsorted(sample["runs"], few), np.searchsorted(sample["runs"], few, "right")
    hit = np.flatnonzero(hi > lo)
    if not len(hit):
        return []
    n = (hi - lo)[hit]
    at = np.repeat(lo[hit] - (np.cumsum(n) - n), n) + np.arange(n.sum())
    common = np.bincount(sample["owner"][at], minlength=len(sample["size"]))
    near = np.flatnonzero((common >= threshold * (sample["size"] + len(hashes) - common) - 1e-9) & ((common < sample["size"]) | (len(hashes) > common)))
    return [common_prefix(sample["labels"][k], own) for k in near.tolist()]


def signatures(docs: DataFrame, threshold: float = THRESHOLD, trees: int = TREES, with_labels: bool = True, sample: dict | None = None) -> DataFrame:
    """(doc_id, mark, node, labels and met, or shingles): ``node`` is a 128-bit name of the shingle set, null for an empty one.

    ``mark`` is a hash of the text; ``met`` tells of links with sampled sets, as prefixes.
    """
    schema = "doc_id long, mark long, node binary, " + ("labels binary, met array<int>" if with_labels else "shingles binary")
    names = [x.split(" ")[0] for x in schema.split(", ")]
    state = docs.sparkSession.sparkContext.broadcast(pickle.dumps(sample or {"runs": []}))  # of bounded size, see QUERY_RUNS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, asked = Words(), pickle.loads(state.value)
        asked["seen"] = np.zeros(1 << 22, bool)  # by the upper 22 bits of a run
        asked["seen"][np.asarray(asked["runs"], np.uint64) >> _SEEN] = True
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                nodes, values, met = [], [], []
                for t in part.column(2).to_pylist():
                    s = shingles(t, table_=words)
                    nodes.append(_name(s) if len(s) else None)
                    if with_labels:
                        own = labels(s, trees) if len(s) else None
                        values.append(own.tobytes() if len(s) else None)
                        met.append(_links_of_sample(asked, s, own, threshold) if len(s) else [])
                    else:
                        values.append(s.tobytes() if len(s) else None)
                arrays = [part.column(0), part.column(1), pa.array(nodes, pa.binary()), pa.array(values, pa.binary())]
                yield pa.RecordBatch.from_arrays([*arrays, pa.array(met, pa.list_(pa.int32()))] if with_labels else arrays, names=names)

    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("mark"), "text").mapInArrow(run, schema)


def _intersections(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections, by products of 0/1 matrices over the hashes that occur on both sides."""
    l_rows = np.repeat(np.arange(len(left)), [len(x) for x in left])
    r_rows = np.repeat(np.arange(len(right)), [len(x) for x in right])
    l_all, r_all = np.concatenate(left), np.concatenate(right)
    both = np.intersect1d(l_all, r_all)
    out = np.zeros((len(left), len(right)), np.float32)
    l_at, r_at = np.searchsorted(both, l_all), np.searchsorted(both, r_all)
    l_ok = (l_at < len(both)) & (both[np.minimum(l_at, len(both) - 1)] == l_all) if len(both) else np.zeros(len(l_all), bool)
    r_ok = (r_at < len(both)) & (both[np.minimum(r_at, len(both) - 1)] == r_all) if len(both) else np.zeros(len(r_all), bool)
    l_rows, l_at, r_rows, r_at = l_rows[l_ok], l_at[l_ok], r_rows[r_ok], r_at[r_ok]
    for a in range(0, len(both), 8192):
        width = min(8192, len(both) - a)
        x, y = np.zeros((len(left), width), np.float32), np.zeros((len(right), width), np.float32)
        m = (l_at >= a) & (l_at < a + width)
        x[l_rows[m], l_at[m] - a] = 1
        m = (r_at >= a) & (r_at < a + width)
        y[r_rows[m], r_at[m] - a] = 1
        out += x @ y.T
    return out


def _roots(n: int, pairs: np.ndarray) -> np.ndarray:
    parent = np.arange(n)

    def top(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = top(a), top(b)
        if a != b:
            parent[max(a, b)] = min(a, b)
    return np.array([top(k) for k in range(n)])


def _verify(threshold: float):
    def run(unit: pd.DataFrame) -> pd.DataFrame:
        unit = unit.drop_duplicates("node").sort_values("node", ignore_index=True)
        i, j, tree = unit["i"][0], unit["j"][0], int(unit["tree"][0])
        sets = [np.frombuffer(x, np.uint64) for x in unit["shingles"]]
        keys = unit["kept"].tolist()
        block = unit["block"].to_numpy()
        rows, cols = np.flatnonzero(block == i), np.flatnonzero(block == j)
        none = pd.DataFrame({"node": [], "root": [], "links": []}).astype({"links": "int64"})
        if not len(rows) or not len(cols):
            return none
        inter = _intersections([sets[k] for k in rows], [sets[k] for k in cols]).astype(np.float64)
        size = np.array([len(s) for s in sets], np.float64)
        near = inter >= threshold * (size[rows][:, None] + size[cols][None, :] - inter) - 1e-9
        for t in range(tree):  # a pair that already met in an earlier tree's bucket was counted there
            code = pd.factorize(np.array([k[t] or None for k in keys], object))[0]  # -1 for none
            near &= ~((code[rows][:, None] == code[cols][None, :]) & (code[rows][:, None] >= 0))
        near &= rows[:, None] < cols[None, :] if i == j else True
        r, c = np.nonzero(near)
        if not len(r):
            return none
        copies = unit["copies"].to_numpy()
        links = np.zeros(len(unit), np.int64)
        np.add.at(links, rows[r], copies[cols[c]])
        np.add.at(links, cols[c], copies[rows[r]])
        roots = _roots(len(unit), np.stack([rows[r], cols[c]], 1))
        hit = np.flatnonzero(links)
        nodes = unit["node"].to_numpy()
        return pd.DataFrame({"node": nodes[hit], "root": nodes[roots[hit]], "links": links[hit]})

    return run


def forest(docs: DataFrame, threshold: float = THRESHOLD, trees: int = TREES) -> tuple[DataFrame, int]:
    """Labels of all rows (doc_id, mark, node, labels), and the prefix at which links are looked for."""
    with small_batches(docs.sparkSession):
        sample = _sampled(docs, QUERIES, QUERY_RUNS) if trees == TREES else None
        rows = persist_table(signatures(docs, threshold, trees, sample=sample), "forest")
    met = [0] * (DEPTH + 1)
    for r in rows.where("size(met) > 0").select(F.explode("met").alias("p")).groupBy("p").count().collect():  # at most DEPTH + 1 rows
        met[r["p"]] = r["count"]
    return rows.drop("met"), prefix_length(threshold, trees, met=met)


def members(docs: DataFrame, threshold: float = THRESHOLD, trees: int = TREES, block: int = BLOCK) -> DataFrame:
    """One row per document: doc_id, mark (a hash of its text), first (doc_id and mark of its class's first row), n_links.

    ``first`` is the least (doc_id, mark) of the rows whose doc_id is not null, if any.
    """
    rows, prefix = forest(docs, threshold, trees)
    place = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark")
    # ``home``: one row that has the set, to find its text again
    sets = persist_table(rows.where("node is not null").groupBy("node").agg(F.count("*").alias("copies"), F.min(place).alias("home"), F.first("labels").alias("labels")), "forest-sets")
    nodes = F.transform(F.sequence(F.lit(0), F.lit(trees - 1)), lambda t: F.substring("labels", t * (DEPTH * STEP) + 1, F.lit(prefix * STEP)))
    met = sets.select("node", F.posexplode(nodes).alias("tree", "key"))
    mark = [F.sum(F.xxhash64("node").cast("decimal(38,0)")), F.bit_xor(F.xxhash64(F.lit(3), "node"))]
    shared = met.groupBy("tree", "key").agg(F.count("*").alias("n"), mark[0].alias("m0"), mark[1].alias("m1")).where("n > 1")
    shared = shared.groupBy("n", "m0", "m1").agg(F.min(F.struct("tree", "key")).alias("b")).select("b.*", "n")
    below = met.join(persist_table(shared, "forest-nodes"), ["tree", "key"])
    kept = persist_table(below.groupBy("node").agg(F.collect_list(F.struct("tree", "key", "n")).alias("in_")), "forest-kept")
    cand = persist_table(sets.join(kept, "node").select("node", "copies", "home", "in_"), "forest-candidates")
    # The text of each candidate's home row; rows that repeat id and text bring a set twice, the verifier drops the second.
    homes = cand.select(F.col("home.doc_id").alias("home_id"), F.col("home.mark").alias("home_mark"), F.col("home.no_id").alias("no_id")).distinct()
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    texts = own.join(homes.where("not no_id"), (F.col("doc_id") == F.col("home_id")) & (F.xxhash64("text") == F.col("home_mark")), "left_semi")
    nameless = own.where("doc_id is null").join(homes.where("no_id"), F.xxhash64("text") == F.col("home_mark"), "left_semi")
    nameless = nameless.groupBy(F.xxhash64("text").alias("m")).agg(F.first("text").alias("text")).select(F.lit(None).cast("long").alias("doc_id"), "text")
    found = signatures(texts.union(nameless), threshold, trees, with_labels=False).select("node", "shingles")
    full = found.join(cand.drop("home"), "node")
    by_tree = F.transform(F.sequence(F.lit(0), F.lit(trees - 1)), lambda t: F.coalesce(F.get(F.filter("in_", lambda x: x["tree"] == t), F.lit(0))["key"], F.lit(b"")))
    full = full.select("node", "copies", "shingles", by_tree.alias("kept"), F.explode("in_").alias("b")).select("*", "b.*").drop("b")
    full = full.withColumn("blocks", F.ceil(F.col("n") / block).cast("int")).withColumn("block", F.pmod(F.xxhash64(F.lit(11), "node"), F.col("blocks")).cast("int"))
    full = full.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    units = full.select("tree", "key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "node", "copies", "shingles", "kept")
    linked = units.groupBy("tree", "key", "i", "j").applyInPandas(_verify(threshold), "node binary, root binary, links long")
    with small_batches(docs.sparkSession):
        linked = persist_table(linked, "forest-links")
    parts = connected_components(linked.select(F.col("node").alias("a"), F.col("root").alias("b")))
    links = linked.groupBy("node").agg(F.sum("links").alias("links"))
    named = sets.select("node", "copies", "home").join(parts, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = named.groupBy("root").agg(F.min("home").alias("first"))
    each = persist_table(named.join(least, "root").join(links, "node", "left").select("node", "first", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links")), "forest-classes")
    out = ["doc_id", "mark", F.struct("first.doc_id", "first.mark").alias("first"), "n_links"]
    with_set = rows.where("node is not null").select("doc_id", "mark", "node").join(each, "node").select(*out)
    return with_set.union(rows.where("node is null").select("doc_id", "mark", F.struct("doc_id", "mark"), F.lit(0).cast("long")))


def classes(docs: DataFrame, threshold: float = THRESHOLD, trees: int = TREES, block: int = BLOCK) -> DataFrame:
    """One row per document: doc_id, class_id (least doc_id reachable by links), n_links (other documents linked directly)."""
    return members(docs, threshold, trees, block).select("doc_id", F.col("first.doc_id").alias("class_id"), "n_links")


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents", "doc_id", "text"))
