"""Step 2b: components, greedy conflict-aware partitioning, objectives."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mapforge.params import SynthParams
from mapforge.sources.storage import drop, stage


#: Edge lists up to this length are solved in one task; longer ones in distributed rounds. Both give the same rows.
LOCAL_EDGES = 10_000
#: Nodes with more edges than this (and than a 500th of all) are looked up by broadcast, so none makes a hot join key.
HOT_EDGES = 200


def _top(parent: dict, x):
    while parent[x] != x:
        parent[x] = parent[parent[x]]
        x = parent[x]
    return x


def _join(parent: dict, pdf: pd.DataFrame) -> None:
    """Join the ends of the rows of two columns; the least node of a component is its top."""
    for a, b in zip(pdf.iloc[:, 0], pdf.iloc[:, 1]):
        parent.setdefault(a, a)
        parent.setdefault(b, b)
        a, b = _top(parent, a), _top(parent, b)
        if a != b:
            parent[max(a, b)] = min(a, b)


def _least_reachable(pdf: pd.DataFrame) -> pd.DataFrame:
    parent: dict = {}
    _join(parent, pdf[["u", "v"]])
    nodes = list(parent)
    return pd.DataFrame({"node": pd.Series(nodes, dtype=object), "comp": pd.Series([_top(parent, x) for x in nodes], dtype=object)})


def thinned(edges: DataFrame) -> DataFrame:
    """(src, dst) of fewer edges that join the same nodes: each partition keeps a star for each of its components."""

    def run(it: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        parent: dict = {}
        for pdf in it:
            _join(parent, pdf)
        nodes = [x for x in parent if parent[x] != x]
        yield pd.DataFrame({"src": pd.Series(nodes, dtype=object), "dst": pd.Series([_top(parent, x) for x in nodes], dtype=object)})

    ends = edges.select("src", "dst").where("src is not null and dst is not null")
    return ends.mapInPandas(run, f"src {dict(ends.dtypes)['src']}, dst {dict(ends.dtypes)['dst']}")


def _with_least(rows: DataFrame, low: DataFrame, n_edges: int, hot_edges: int) -> DataFrame:
    """``rows`` (u, v) with the ``m`` of their u from ``low`` (u, m, n): one row per u with its number n of edges.

    At most 1,000 nodes can have more than a 500th of the edges, so the broadcast side is bounded.
    """
    limit = max(hot_edges, n_edges // 500)
    hot = low.where(F.col("n") > limit).select("u", F.col("m").alias("hot_m"))
    marked = rows.join(F.broadcast(hot), "u", "left")
    few = marked.where("hot_m is null").select("u", "v").join(low.where(F.col("n") <= limit).select("u", "m"), "u")
    return few.union(marked.where("hot_m is not null").select("u", "v", F.col("hot_m").alias("m")))


def components(edges: DataFrame, max_rounds: int = 100, local_edges: int = LOCAL_EDGES, hot_edges: int = HOT_EDGES) -> DataFrame:
    """(node, comp) for each node of the undirected (src, dst); comp is the least node that can be reached.

    Short edge lists are solved in one task. Longer ones by alternating large-star and small-star contraction:
    each round is two aggregations and two joins on the edge list, whose length never grows, so no component is
    gathered in one task, and star centres never make a hot join key. A round that changes nothing ends it; its end
    is seen through a count and a hash sum only. Raises where ``max_rounds`` do not suffice. Edges with a null end
    and loops are left out; no edges give no rows.
    """
    spark = edges.sparkSession
    cur = stage(edges.where("src is not null and dst is not null").select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).where("u <> v").distinct(), "comp")
    kind = dict(cur.dtypes)["u"]

    def stamp(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    mark = stamp(cur)
    if mark[0] <= local_edges:
        return cur.groupBy(F.lit(0).alias("all")).applyInPandas(_least_reachable, f"node {kind}, comp {kind}")
    for _ in range(max_rounds):
        both = cur.union(cur.select(F.col("v"), F.col("u")))
        low = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n")
        large = _with_least(both, low, mark[0], hot_edges).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = stage(large.where("u <> v").distinct(), "comp")
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        small = _with_least(large, low, mark[0], hot_edges).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        nxt = stage(small.union(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct(), "comp")
        drop(large)
        drop(cur)
        cur, new = nxt, stamp(nxt)
        if new == mark:
            break
        mark = new
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return cur.select(F.col("u").alias("node"), F.col("v").alias("comp")).union(cur.select(F.col("v"), F.col("v")).distinct())


def merge_greedily(edges: list[tuple[str, str, float, float]], p: SynthParams) -> dict[str, str]:
    """Partition one component: join the two parts with most positive weight between them until none may join.

    Ties go to the smaller least member, then to the smaller other one. A part is named by its least member.
    """
    weight: dict[str, dict[str, float]] = {}
    block: dict[str, dict[str, float]] = {}
    for a, b, pos, neg in edges:
        for x, y in ((a, b), (b, a)):
            weight.setdefault(x, {})
            block.setdefault(x, {})
            if pos >= p.theta_edge and pos > 0:
                weight[x][y] = pos
            if neg < 0 and p.use_negative:
                block[x][y] = neg
    part = {v: v for v in weight}
    members = {v: [v] for v in weight}
    heap = [(-round(w, 9), a, b) for a in weight for b, w in weight[a].items() if a < b]
    heapq.heapify(heap)
    while heap:
        w, a, b = heapq.heappop(heap)
        if a not in members or b not in members or round(weight[a].get(b, 0), 9) != -w:
            continue
        if block[a].get(b, 0.0) < p.tau:
            continue
        for c, x in weight.pop(b).items():
            del weight[c][b]
            if c != a:
                weight[a][c] = weight[c][a] = weight[a].get(c, 0.0) + x
                heapq.heappush(heap, (-round(weight[a][c], 9), min(a, c), max(a, c)))
        for c, x in block.pop(b).items():
            del block[c][b]
            if c != a:
                old = block[a].get(c, 0.0)
                block[a][c] = block[c][a] = min(old, x) if p.neg_update == "min" else old + x
        members[a] += members.pop(b)
    for top, own in members.items():
        for v in own:
            part[v] = top
    return part


def merge_in_rounds(edges: DataFrame, p: SynthParams, max_rounds: int = 200) -> DataFrame:
    """(cand_id, cluster_id) as :func:`merge_greedily` would make them, but without a task that holds a component.

    In each round two parts join where each is the other's best allowed partner; edges are then added up between the new parts.
    The heaviest allowed edge of all is always such a pair, so rounds go on until no two parts may join. Merges far apart happen
    in one round, so where a later sum would have overtaken an earlier weight the result can differ from the one-by-one order;
    no strong conflict is ever inside a part.
    """
    strong = F.when((F.col("w_pos") >= p.theta_edge) & (F.col("w_pos") > 0), F.col("w_pos")).otherwise(F.lit(0.0))
    conflict = F.least("w_neg", F.lit(0.0)) if p.use_negative else F.lit(0.0)
    live = stage(edges.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), strong.alias("w"), conflict.alias("neg")), "merge-edges")
    part = stage(live.select(F.col("a").alias("cand_id")).union(live.select("b")).distinct().withColumn("cluster_id", F.col("cand_id")), "merge-parts")
    join = F.min if p.neg_update == "min" else F.sum
    for _ in range(max_rounds):
        allowed = live.where((F.col("w") > 0) & (F.col("neg") >= p.tau))
        rank = F.struct((-F.round("w", 9)).alias("w"), "a", "b")
        best = allowed.select(F.col("a").alias("x"), rank.alias("best")).union(allowed.select("b", rank)).groupBy("x").agg(F.min("best").alias("best"))
        pairs = best.groupBy("best.a", "best.b").agg(F.count("*").alias("n")).where("n = 2")
        joined = stage(pairs.select(F.col("b").alias("old"), F.col("a").alias("new")), "merge-joined")
        if joined.isEmpty():
            break
        nxt = live
        for end in ("a", "b"):
            nxt = nxt.join(joined.withColumnRenamed("old", end), end, "left").withColumn(end, F.coalesce("new", end)).drop("new")
        nxt = nxt.where("a <> b").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum("w").alias("w"), join("neg").alias("neg"))
        live, last = stage(nxt, "merge-edges"), live
        part, before = stage(part.join(joined.withColumnRenamed("old", "cluster_id"), "cluster_id", "left").select("cand_id", F.coalesce("new", "cluster_id").alias("cluster_id")), "merge-parts"), part
        drop(last)
        drop(before)
    else:
        raise RuntimeError(f"merging did not end in {max_rounds} rounds")
    names = part.groupBy("cluster_id").agg(F.min("cand_id").alias("least"))
    return part.join(names, "cluster_id").select("cand_id", F.col("least").alias("cluster_id"))


def synthesize(nodes: DataFrame, edges: DataFrame, p: SynthParams | None = None) -> DataFrame:
    """(cand_id, cluster_id): divide by positive components, then partition each one in a task of its own, giant ones in rounds."""
    p = p or SynthParams()
    edges = stage(edges, "edges")
    comp = stage(components(edges.where((F.col("w_pos") >= p.theta_edge) & (F.col("w_pos") > 0))), "parts")
    inside = edges.join(comp.select(F.col("node").alias("src"), "comp"), "src").join(comp.select(F.col("node").alias("dst"), F.col("comp").alias("comp2")), "dst").where("comp = comp2")
    inside = stage(inside.select("comp", "src", "dst", "w_pos", "w_neg"), "inside")
    giant = [r["comp"] for r in inside.groupBy("comp").agg(F.count("*").alias("n")).where(F.col("n") > p.task_edges).collect()]  # each has so many edges

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        got = merge_greedily(list(zip(pdf["src"], pdf["dst"], pdf["w_pos"], pdf["w_neg"])), p)
        return pd.DataFrame({"cand_id": list(got), "cluster_id": list(got.values())})

    small = inside.where(~F.col("comp").isin(giant)) if giant else inside
    found = small.groupBy("comp").applyInPandas(run, "cand_id string, cluster_id string")
    if giant:
        found = found.union(merge_in_rounds(inside.where(F.col("comp").isin(giant)), p))
    found = nodes.select("cand_id").distinct().join(found, "cand_id", "left").select("cand_id", F.coalesce("cluster_id", "cand_id").alias("cluster_id"))
    return stage(found, "assign")  # its size is then known, so joins with pairs never broadcast the pairs


def _ends(assign: DataFrame, edges: DataFrame) -> DataFrame:
    a = assign.select(F.col("cand_id").alias("src"), F.col("cluster_id").alias("c1"))
    b = assign.select(F.col("cand_id").alias("dst"), F.col("cluster_id").alias("c2"))
    return edges.join(a, "src").join(b, "dst")


def objective(assign: DataFrame, edges: DataFrame, tau: float = -0.2) -> DataFrame:
    """One row: score (positive weight inside), loss (positive weight cut), violations (strong negative edges inside)."""
    same = F.col("c1") == F.col("c2")
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("w_pos"))), F.lit(0.0))
    return _ends(assign, edges).agg(total(same).alias("score"), total(~same).alias("loss"), F.count_if(same & (F.col("w_neg") < tau)).alias("violations"))
