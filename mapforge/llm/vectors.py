"""Operator 5: near-duplicate embeddings through an inverted multi-index.

Unit vectors are cut in halves; each half has its own codebook (k-means on a bounded sample), and
the product of both codebooks is a grid of cells. A vector visits cells by multi-sequence traversal:
best sums of half distances first, cells in use or not, up to a number of cells that reaches the target
recall for ``QUERIES`` sampled vectors, each compared exactly with every vector of the input. Every vector
is in the index and every vector queries it.
A pair is compared when either side visits the other's cell, and verified by cosine in double precision.

Equal vectors fall into one class first. Cells are cut into blocks; a task compares a block of queries
with a block of a cell by one matrix product and returns, per class, its number of links and a root,
never pairs. A pair both of whose sides visit each other is counted once.

Vectors meet others of their own length only; each length that more than ``FEW_VECTORS`` distinct vectors have gets an
index of its own, the vectors of a rarer length are one cell, all compared. Vectors that are null, zero, or hold null
or non-finite components link with nothing and stand alone. Rows with a null vec_id link as others do and name a
component only where no other row is in it. Repeated rows link with each other; an empty table gives no rows.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import connected_components, persist_table, table
from mapforge.llm.neardup import _roots

THRESHOLD = 0.95
CELL_ROWS = 64
SAMPLE = 8000
RECALL = 0.995
MAX_VISITS = 64
QUERIES = 1000
FEW = 30
FEW_VECTORS = 2000
BLOCK = 256


def _kmeans(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    rng = np.random.default_rng(5)
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = _nearest(x, centres).argmin(1)
        for c in range(len(centres)):
            if (near == c).any():
                centres[c] = x[near == c].mean(0)
    return centres


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return (x * x).sum(1)[:, None] - 2 * x @ centres.T + (centres * centres).sum(1)[None, :]


def traverse(d1: np.ndarray, d2: np.ndarray, visits: int) -> np.ndarray:
    """Cells (first code * codes + second code) by rising sum of half distances, ``visits`` of them per row.

    A cell whose codes rank r and s in their halves is preceded by (r + 1)(s + 1) - 1 cells at least,
    so only cells with (r + 1)(s + 1) <= visits can be among the first: those are merged by one sort.
    """
    o1, o2 = d1.argsort(1), d2.argsort(1)
    ranks = np.array([(r, s) for r in range(min(visits, d1.shape[1])) for s in range(min(visits // (r + 1), d2.shape[1]))])
    rows = np.arange(len(d1))[:, None]
    c1, c2 = o1[:, ranks[:, 0]], o2[:, ranks[:, 1]]
    total = d1[rows, c1] + d2[rows, c2]
    best = np.argsort(total, axis=1, kind="stable")[:, :visits]
    return c1[rows, best] * d2.shape[1] + c2[rows, best]


def codes_for(n: int, sample: int = SAMPLE) -> int:
    """Codes of a half's codebook, so that a cell of the grid holds about ``CELL_ROWS`` of ``n`` vectors, and a code eight of the sample or more."""
    return max(4, min(round((n / CELL_ROWS) ** 0.5), sample // 8))


def fit(x: np.ndarray, codes: int) -> dict:
    """Codebooks for both halves of unit vectors, with the largest number of visits."""
    half = x.shape[1] // 2 or 1
    books = (_kmeans(x[:, :half], codes), _kmeans(x[:, half:], codes))
    return {"half": half, "books": books, "visits": min(MAX_VISITS, len(books[0]) * len(books[1])), "dim": x.shape[1]}


def _units(y: np.ndarray) -> np.ndarray:
    y = y / abs(y).max(1, keepdims=True)
    return y / np.linalg.norm(y, axis=1, keepdims=True)


def _ranks(state, threshold: float):
    """Per task: how many links of each query first meet at each number of visits, and each query's nearest vector with its rank."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, q_nodes, qx = pickle.loads(state.value)
        most, q_seen = model["visits"], cells(model, qx)
        counts = np.zeros((len(qx), most + 1), np.int64)
        near, near_rank = np.full(len(qx), -2.0), np.full(len(qx), most)

        def meet(r: np.ndarray, c: np.ndarray, seen: np.ndarray) -> np.ndarray:
            at = lambda hit: np.where(hit.any(1), hit.argmax(1), most)
            return np.minimum(at(q_seen[r] == seen[c, :1]), at(seen[c] == q_seen[r, :1]))

        for whole in batches:
            for i in range(0, whole.num_rows, 500):
                part = whole.slice(i, 500)
                y = _units(np.array(part.column("v").to_pylist()))
                seen = cells(model, y)
                cos = np.where(q_nodes[:, None] == np.array(part.column("node").to_pylist(), dtype=object)[None, :], -2.0, qx @ y.T)
                r, c = np.nonzero(cos >= threshold)
                for a in range(0, len(r), 20_000):  # for bounded memory
                    np.add.at(counts, (r[a : a + 20_000], meet(r[a : a + 20_000], c[a : a + 20_000], seen)), 1)
                best = cos.argmax(1)
                new = np.flatnonzero(cos[np.arange(len(qx)), best] > near)
                near[new], near_rank[new] = cos[new, best[new]], meet(new, best[new], seen)
        q, k = np.nonzero(counts)
        found = np.flatnonzero(near > -2)
        cols = [np.concatenate([q, found]), np.concatenate([k, near_rank[found]]), np.concatenate([counts[q, k], np.zeros(len(found), np.int64)]), np.concatenate([np.full(len(q), -2.0), near[found]])]
        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(cols, (pa.int32(), pa.int32(), pa.int64(), pa.float64()))], names=["query", "rank", "n", "cos"])

    return run


def calibrate(sets: DataFrame, model: dict, nodes: np.ndarray, x: np.ndarray, threshold: float, recall: float = RECALL) -> int | None:
    """The number of visits with which the queries ``x`` reach the recall; None if their links need more than the most there are.

    Each query counts once, by the visits that bring in the target share of its own links, so that no large group decides.
    With links at fewer than ``FEW`` queries, the others count by their nearest vector.
    """
    most = model["visits"]
    state = sets.sparkSession.sparkContext.broadcast(pickle.dumps((model, nodes, x)))
    rows = persist_table(sets.select("node", "v").mapInArrow(_ranks(state, threshold), "query int, rank int, n long, cos double"), "vector-ranks")
    counts = np.zeros((len(x), most + 1), np.int64)
    for r in rows.where("n > 0").groupBy("query", "rank").agg(F.sum("n").alias("n")).collect():
        counts[r["query"], r["rank"]] = r["n"]
    linked = np.flatnonzero(counts.sum(1))
    share = counts[linked].cumsum(1) / counts[linked].sum(1, keepdims=True)
    needed = (share >= recall).argmax(1)
    if len(linked) and np.quantile(needed, recall) >= most and most == MAX_VISITS:
        return None
    if len(linked) < FEW:
        nearest = rows.where("n = 0").groupBy("query").agg(F.max_by("rank", "cos").alias("rank")).collect()
        needed = np.concatenate([needed, [r["rank"] for r in nearest if r["query"] not in set(linked.tolist())]])
    if not len(needed):
        return most
    return int(min(most, max(4, 2 * (np.quantile(needed, recall) + 1))))


def cells(model: dict, x: np.ndarray) -> np.ndarray:
    h, some = model["half"], 2000  # rows at a time, for bounded memory
    parts = [x[a : a + some] for a in range(0, len(x), some)]
    return np.concatenate([traverse(_nearest(p[:, :h], model["books"][0]), _nearest(p[:, h:], model["books"][1]), model["visits"]) for p in parts])


def _fitted(sets: DataFrame, dim: int, n: int, threshold: float, sample: int) -> dict:
    """The index for the ``n`` vectors of one length."""
    same = sets.where(F.size("v") == dim)
    picked = [(r["node"], r["v"]) for r in same.orderBy(F.xxhash64("v"), "v").limit(max(sample, QUERIES)).select("node", "v").collect()]
    x, codes = _units(np.array([v for _, v in picked])), codes_for(n, sample)
    asking = np.array([k for k, _ in picked[:QUERIES]], dtype=object)
    while True:
        model = fit(x[:sample], codes)
        visits = calibrate(same, model, asking, x[:QUERIES], threshold)
        if visits is not None or codes < 4:
            return {**model, "visits": visits or model["visits"]}
        codes //= 2  # cells too small for the target recall


def _place(state):
    """Unit vectors with their cells: dimension and code in one number, so that lengths never meet."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = pickle.loads(state.value)
        for whole in batches:
            dims = np.array([len(v) for v in whole.column("v").to_pylist()], np.int64)
            for dim in np.unique(dims).tolist():
                b = whole.take(pa.array(np.flatnonzero(dims == dim)))
                y = _units(np.array(b.column("v").to_pylist()))
                seen = (cells(models[dim], y) if dim in models else np.zeros((len(y), 1), np.int64)) + (dim << 40)
                yield pa.RecordBatch.from_arrays([b.column("node"), b.column("copies"), pa.array([v.astype("<f8").tobytes() for v in y], pa.binary()), pa.array(seen[:, 0]), pa.array(seen.tolist(), pa.list_(pa.int64()))], names=["node", "copies", "unit", "home", "visits"])

    return run


def _compare(threshold: float):
    def run(unit: pd.DataFrame) -> pd.DataFrame:
        cell = unit["cell"][0]
        query = unit["query"].to_numpy()
        q, t = unit[query], unit[~query]
        none = pd.DataFrame({"node": [], "root": [], "links": []}).astype("int64")
        if not len(q) or not len(t):
            return none
        x, y = (np.array([np.frombuffer(v, "<f8") for v in s["unit"]]) for s in (q, t))
        near = x @ y.T >= threshold
        qn, tn = q["node"].to_numpy(), t["node"].to_numpy()
        near &= qn[:, None] != tn[None, :]
        r, c = np.nonzero(near)
        if not len(r):
            return none
        q_home, t_visits = q["home"].to_numpy(), [set(v.tolist()) for v in t["visits"]]
        # the pair also meets in the query's own cell if the target visits it: then each side counts for itself
        back = np.array([q_home[a] in t_visits[b] for a, b in zip(r, c)])
        nodes, at = np.unique(np.concatenate([qn, tn]), return_inverse=True)
        qi, ti = at[: len(qn)], at[len(qn) :]
        links = np.zeros(len(nodes), np.int64)
        np.add.at(links, qi[r], t["copies"].to_numpy()[c])
        np.add.at(links, ti[c[~back]], q["copies"].to_numpy()[r[~back]])
        roots = _roots(len(nodes), np.stack([qi[r], ti[c]], 1))
        hit = np.flatnonzero((links > 0) | (roots != np.arange(len(nodes))))
        del cell
        return pd.DataFrame({"node": nodes[hit], "root": nodes[roots[hit]], "links": links[hit]})

    return run


def link(vectors: DataFrame, threshold: float = THRESHOLD, sample: int = SAMPLE, block: int = BLOCK, few: int = FEW_VECTORS) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of ``vectors`` (vec_id, embedding)."""
    spark = vectors.sparkSession
    clean = vectors.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("v"))
    usable = F.coalesce(
        F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists("v", lambda x: x != 0), F.lit(False)
    )
    rows = clean.select("vec_id", F.when(usable, F.transform("v", lambda x: x + F.lit(0.0))).alias("v"))
    # two hashes of 64 bits stand for a vector's value where rows are dealt by it
    rows = persist_table(rows.withColumns({"k": F.when(F.col("v").isNotNull(), F.xxhash64("v")), "k2": F.xxhash64(F.lit(7), "v")}), "vectors")
    # a class of equal vectors is named by its least id
    least = F.min("vec_id")
    sets = persist_table(rows.where("v is not null").groupBy("k", "k2").agg(F.first("v").alias("v"), least.alias("least"), F.coalesce(least, F.first("k")).alias("node"), F.count("*").alias("copies")), "vector-classes")
    linked = spark.createDataFrame([], "node long, root long, links long")
    lengths = {r["dim"]: r["n"] for r in sets.groupBy(F.size("v").alias("dim")).agg(F.count("*").alias("n")).collect()}
    if lengths:
        models = {dim: _fitted(sets, dim, n, threshold, sample) for dim, n in sorted(lengths.items()) if n > few}
        state = spark.sparkContext.broadcast(pickle.dumps(models))
        placed = persist_table(sets.select("node", "copies", "v").mapInArrow(_place(state), "node long, copies long, unit binary, home long, visits array<long>"), "vector-cells")
        full = placed.groupBy("home").agg(F.count("*").alias("n")).select(F.col("home").alias("cell"), F.ceil(F.col("n") / block).cast("int").alias("t_blocks"))
        asked = placed.select(F.explode("visits").alias("cell")).groupBy("cell").agg(F.ceil(F.count("*") / block).cast("int").alias("q_blocks"))
        grid = full.join(asked, "cell")  # a row per cell in use: at most codes x codes
        part = lambda salt, n: F.pmod(F.xxhash64(F.lit(salt), "node"), F.col(n)).cast("int")
        span = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
        q = placed.select("*", F.explode("visits").alias("cell")).join(F.broadcast(grid), "cell").withColumn("qb", part(1, "q_blocks")).withColumn("tb", span("t_blocks"))
        t = placed.withColumn("cell", F.col("home")).join(F.broadcast(grid), "cell").withColumn("tb", part(2, "t_blocks")).withColumn("qb", span("q_blocks"))
        cols = ["cell", "qb", "tb", "query", "node", "copies", "unit", "home", "visits"]
        units = q.withColumn("query", F.lit(True)).select(cols).union(t.withColumn("query", F.lit(False)).select(cols))
        linked = persist_table(units.groupBy("cell", "qb", "tb").applyInPandas(_compare(threshold), "node long, root long, links long"), "vector-links")
    parts = connected_components(linked.select(F.col("node").alias("a"), F.col("root").alias("b")))
    links = linked.groupBy("node").agg(F.sum("links").alias("links"))
    each = sets.select("k", "k2", "node", "least", "copies").join(parts, "node", "left").withColumn("root", F.coalesce("root", "node"))
    named = persist_table(each.groupBy("root").agg(F.min("least").alias("component_id")), "vector-components")
    each = each.join(named, "root").join(links, "node", "left")
    each = persist_table(each.select("k", "k2", "component_id", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links")), "vector-found")
    done = rows.where("v is not null").select("vec_id", "k", "k2").join(each, ["k", "k2"]).select("vec_id", "n_links", "component_id")
    done = done.union(rows.where("v is null").select("vec_id", F.lit(0).cast("long"), F.col("vec_id")))
    return done.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op5_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))
