"""Partitioning as a linear programme over distances, solved per small component, and its rounding.

Every vertex pair has a distance between 0 (same part) and 1 (parted) under the triangle inequality; pairs with a strong
negative edge are at distance 1, and the positive weight times distance is minimised. The optimum bounds the loss of every
feasible partition from below. Rounding grows balls of radius below one half, so the two ends of a negative edge never
share one. The number of triangles is cubic: this is for components of ``max_n`` vertices at most.
"""

from __future__ import annotations

import itertools

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mapforge.operators.exact import Edge

MAX_N = 12


def dual_simplex(c: np.ndarray, a: np.ndarray, b: np.ndarray, max_steps: int = 20_000) -> np.ndarray:
    """x >= 0 minimising c x under a x <= b, for c >= 0 and b of any sign: slack columns are a dual feasible start."""
    rows, cols = a.shape
    t = np.hstack([a, np.eye(rows), b[:, None]]).astype(float)
    cost = np.concatenate([c.astype(float), np.zeros(rows)])
    basis = np.arange(cols, cols + rows)
    for _ in range(max_steps):
        low = t[:, -1] < -1e-9
        if not low.any():
            x = np.zeros(cols + rows)
            x[basis] = t[:, -1]
            return x[:cols]
        leave = min(np.flatnonzero(low), key=lambda k: basis[k])
        can = np.flatnonzero(t[leave, :-1] < -1e-9)
        if not len(can):
            raise ValueError("no feasible distances")
        ratio = cost[can] / -t[leave, can]
        enter = can[np.flatnonzero(ratio <= ratio.min() + 1e-12)[0]]
        t[leave] /= t[leave, enter]
        others = np.arange(rows) != leave
        t[others] -= np.outer(t[others, enter], t[leave])
        cost = cost - cost[enter] * t[leave, :-1]
        basis[leave] = enter
    raise RuntimeError("the programme took too many steps")


def distances(edges: list[Edge], tau: float = -0.2, max_n: int = MAX_N) -> tuple[float, list[str], np.ndarray]:
    """Least loss of the relaxation, the vertices in order, and the matrix of their distances.

    Triangles enter only once they are violated.
    """
    nodes = sorted({v for e in edges for v in e[:2]})
    if len(nodes) > max_n:
        raise ValueError(f"the relaxation is for {max_n} vertices at most")
    at = {v: k for k, v in enumerate(nodes)}
    pairs = list(itertools.combinations(range(len(nodes)), 2))
    var = {p: k for k, p in enumerate(pairs)}
    of = lambda i, j: var[min(i, j), max(i, j)]
    c = np.zeros(len(pairs))
    rows, bounds = list(np.eye(len(pairs))), [1.0] * len(pairs)
    for x, y, pos, neg in edges:
        k = of(at[x], at[y])
        c[k] += max(pos, 0.0)
        if neg < tau:
            rows.append(-np.eye(len(pairs))[k])
            bounds.append(-1.0)
    known: set[tuple[int, int, int]] = set()
    while True:
        d = dual_simplex(c, np.array(rows), np.array(bounds)) if pairs else np.empty(0)
        new = [(i, j, k) for i, j in pairs for k in range(len(nodes)) if k not in (i, j) and (i, j, k) not in known and d[of(i, j)] > d[of(i, k)] + d[of(k, j)] + 1e-7]
        if not new:
            break
        for i, j, k in new:
            row = np.zeros(len(pairs))
            row[of(i, j)], row[of(i, k)], row[of(k, j)] = 1, -1, -1
            rows.append(row)
            bounds.append(0.0)
        known.update(new)
    full = np.zeros((len(nodes), len(nodes)))
    for (i, j), k in var.items():
        full[i, j] = full[j, i] = d[k]
    return float(c @ d), nodes, full


def rounded(edges: list[Edge], tau: float = -0.2, max_n: int = MAX_N) -> tuple[float, float, dict[str, str]]:
    """(lower bound of the loss, loss after rounding, part of each vertex): balls of the best cut for their volume."""
    bound, nodes, d = distances(edges, tau, max_n)
    at = {v: k for k, v in enumerate(nodes)}
    weights = [(at[x], at[y], max(w, 0.0)) for x, y, w, _ in edges]
    bad = [(at[x], at[y]) for x, y, _, neg in edges if neg < tau]
    left, parts = set(range(len(nodes))), []
    while live := [p for p in bad if p[0] in left and p[1] in left]:
        centre = min(live)[0]
        best = None
        for radius in sorted({d[centre, v] for v in left if d[centre, v] < 0.5 - 1e-9} | {0.0}):
            ball = {v for v in left if d[centre, v] <= radius + 1e-9}
            inner = [(x, y, w) for x, y, w in weights if x in left and y in left]
            cut = sum(w for x, y, w in inner if (x in ball) != (y in ball))
            volume = bound / len(nodes) + sum(w * d[x, y] for x, y, w in inner if x in ball or y in ball)
            rank = (cut / volume if volume > 1e-12 else cut, radius)
            if best is None or rank < best[0]:
                best = (rank, ball)
        parts.append(best[1])
        left -= best[1]
    if left:
        parts.append(left)
    home = {v: k for k, p in enumerate(parts) for v in p}
    loss = sum(w for x, y, w in weights if home[x] != home[y])
    return bound, loss, {nodes[v]: nodes[min(parts[home[v]])] for v in home}


def solve_components(edges: DataFrame, comp: DataFrame, tau: float = -0.2, max_n: int = MAX_N) -> DataFrame:
    """(comp, cand_id, cluster_id, bound, loss): each component of at most ``max_n`` vertices in a task of its own.

    Larger ones are listed with null bounds and every vertex alone: they are beyond this method.
    """
    inside = edges.join(comp.select(F.col("node").alias("src"), "comp"), "src").join(comp.select(F.col("node").alias("dst"), F.col("comp").alias("comp2")), "dst").where("comp = comp2")
    n = comp.groupBy("comp").agg(F.count("*").alias("n"))
    sized = inside.join(n, "comp")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        bound, loss, home = rounded(list(zip(pdf["src"], pdf["dst"], pdf["w_pos"], pdf["w_neg"])), tau, max_n)
        return pd.DataFrame({"comp": pdf["comp"].iloc[0], "cand_id": list(home), "cluster_id": list(home.values()), "bound": bound, "loss": loss})

    small = sized.where(F.col("n") <= max_n).select("comp", "src", "dst", "w_pos", "w_neg").groupBy("comp").applyInPandas(run, "comp string, cand_id string, cluster_id string, bound double, loss double")
    alone = comp.join(n.where(F.col("n") > max_n), "comp").select("comp", F.col("node").alias("cand_id"), F.col("node").alias("cluster_id"), F.lit(None).cast("double").alias("bound"), F.lit(None).cast("double").alias("loss"))
    return small.union(alone)
