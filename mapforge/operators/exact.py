"""Exact partitions of small components: enumeration, one negative edge, two negative edges."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Edge = tuple[str, str, float, float]


def partitions(items: list[str]) -> Iterator[list[list[str]]]:
    if not items:
        yield []
        return
    for rest in partitions(items[1:]):
        yield [[items[0]], *rest]
        for k in range(len(rest)):
            yield rest[:k] + [[items[0], *rest[k]]] + rest[k + 1 :]


def score(parts: list[list[str]], edges: list[Edge], tau: float) -> float | None:
    """Positive weight inside parts; None where a strong negative edge is inside."""
    home = {v: k for k, p in enumerate(parts) for v in p}
    inside = [e for e in edges if home[e[0]] == home[e[1]]]
    return None if any(e[3] < tau for e in inside) else sum(e[2] for e in inside)


def enumerate_best(edges: list[Edge], tau: float = -0.2, max_n: int = 9) -> tuple[float, list[list[str]]]:
    nodes = sorted({v for e in edges for v in e[:2]})
    if len(nodes) > max_n:
        raise ValueError(f"enumeration is for {max_n} vertices at most")
    best = (-1.0, [])
    for p in partitions(nodes):
        s = score(p, edges, tau)
        if s is not None and s > best[0] + 1e-12:
            best = (s, sorted(map(sorted, p)))
    return best


def min_cut(edges: list[Edge], sources: set[str], sinks: set[str]) -> tuple[float, set[str]]:
    """Least positive weight between two vertex sets and the sources' side, by shortest augmenting paths."""
    cap: dict[str, dict[str, float]] = {"+": {}, "-": {}}
    for a, b, w, _ in edges:
        for x, y in ((a, b), (b, a)):
            cap.setdefault(x, {})
            cap[x][y] = cap[x].get(y, 0.0) + max(w, 0.0)
    for ends, v in ((sources, "+"), (sinks, "-")):
        for x in ends:
            cap.setdefault(x, {})
            cap[v][x] = cap[x][v] = float("inf")
    flow = 0.0
    while True:
        came, queue = {"+": "+"}, deque(["+"])
        while queue and "-" not in came:
            x = queue.popleft()
            for y, c in cap[x].items():
                if c > 1e-12 and y not in came:
                    came[y] = x
                    queue.append(y)
        if "-" not in came:
            return flow, set(came) - {"+"}
        path, x = [], "-"
        while x != "+":
            path.append((came[x], x))
            x = came[x]
        add = min(cap[x][y] for x, y in path)
        for x, y in path:
            cap[x][y] -= add
            cap[y][x] = cap[y].get(x, 0.0) + add
        flow += add


def solve(edges: list[Edge], tau: float = -0.2, max_n: int = 9) -> float:
    """Best score by the number of strong negative edges: none, one cut, the better of two cuts, or enumeration."""
    bad = [e for e in edges if e[3] < tau]
    total = sum(max(e[2], 0.0) for e in edges)
    if not bad:
        return total
    if len(bad) == 1:
        return total - min_cut(edges, {bad[0][0]}, {bad[0][1]})[0]
    if len(bad) == 2:
        (s1, t1), (s2, t2) = bad[0][:2], bad[1][:2]
        sides = [({s1, s2}, {t1, t2}), ({s1, t2}, {t1, s2})]
        return total - min(min_cut(edges, a, b)[0] for a, b in sides if not a & b)
    return enumerate_best(edges, tau, max_n)[0]


def solve_components(edges: DataFrame, comp: DataFrame, tau: float = -0.2, max_n: int = 9) -> DataFrame:
    """(comp, n, negatives, method, score): the best score of each component of ``edges``, a component in a task of its own.

    ``comp``: (node, comp). Components with up to two strong negative edges are solved by cuts, whatever their size; those
    with more by enumeration up to ``max_n`` vertices, beyond that score is null and method ``none``.
    """
    ends = comp.select(F.col("node").alias("src"), "comp"), comp.select(F.col("node").alias("dst"), F.col("comp").alias("comp2"))
    inside = edges.join(ends[0], "src").join(ends[1], "dst").where("comp = comp2")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = list(zip(pdf["src"], pdf["dst"], pdf["w_pos"], pdf["w_neg"]))
        n, bad = len({v for e in own for v in e[:2]}), sum(e[3] < tau for e in own)
        method = ("whole", "one cut", "two cuts")[bad] if bad <= 2 else "enumeration" if n <= max_n else "none"
        best = None if method == "none" else float(solve(own, tau, max_n))
        return pd.DataFrame({"comp": [pdf["comp"].iloc[0]], "n": [n], "negatives": [bad], "method": [method], "score": pd.Series([best], dtype="float64")})

    return inside.select("comp", "src", "dst", "w_pos", "w_neg").groupBy("comp").applyInPandas(run, "comp string, n long, negatives long, method string, score double")
