"""A corpus as counted sets: every left value with the tables that hold each of its rights, equal ones counted once.

Tables that are compared or united again and again need their rows gathered only once: what two tables share, and how a relation
made of whole tables meets the truth, depend on the sets alone. Tables are numbered; what has one row per table is kept on the driver.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mapforge.sources.storage import stage

#: Pairs of tables that are laid out at once.
CHUNK = 2_000_000
#: Up to this many kinds of pairs are counted in one array, more are sorted.
DENSE = 1 << 22


@dataclass
class Gathered:
    """``sets`` (n, void, sides), ``tables``: (cand_id, domain) by number, ``cases``: case_id by number."""

    sets: DataFrame
    tables: list[tuple[str, str]]
    cases: list[str]


def gather(rows: DataFrame, tables: list[tuple[str, str]], cases: list[str]) -> Gathered:
    """From (l, r, cands, cases): a value pair with numbers of tables and cases that hold it; a pair may have several rows."""
    n_tasks = 4 * rows.sparkSession.sparkContext.defaultParallelism
    sides = rows.repartition(n_tasks, "l").groupBy("l").agg(F.sort_array(F.collect_list(F.struct("r", "cands", "cases"))).alias("s"))
    # sides stand in the order of their rights; ``again`` marks one that goes on with the right before it, ``none`` a null right
    bare = F.expr("transform(s, (x, i) -> struct(x.cands as cands, x.cases as cases, i > 0 and x.r <=> s[greatest(i - 1, 0)].r as again, x.r is null as none))")
    sets = sides.select(F.isnull("l").alias("void"), bare.alias("sides")).groupBy("void", "sides").agg(F.count("*").alias("n"))
    return Gathered(stage(sets.repartition(n_tasks), "sets"), tables, cases)


def of_tables(cands: DataFrame, truth: DataFrame) -> Gathered:
    """From rows (cand_id, domain, l, r) and a truth (case_id, l, r)."""
    tables = sorted(tuple(r) for r in cands.where("cand_id is not null").groupBy("cand_id").agg(F.min("domain")).collect())
    cases = sorted(r[0] for r in truth.select("case_id").distinct().collect())
    none = F.array().cast("array<int>")
    return gather(numbered(cands, tables).select("l", "r", "cands", none.alias("cases")).union(truth.select("l", "r", none, F.array(number("case_id", cases)))), tables, cases)


def number(column: str, names: list[str]):
    return (F.array_position(F.array(*map(F.lit, names)), F.col(column)) - 1).cast("int") if names else F.lit(None).cast("int")


def numbered(cands: DataFrame, tables: list[tuple[str, str]], first: int = 0) -> DataFrame:
    """(l, r, cands) of rows (cand_id, l, r); ``first`` is the number of the first of ``tables``."""
    found = cands.where("cand_id is not null").select("l", "r", (number("cand_id", [t[0] for t in tables]) + first).alias("c"))
    return found.groupBy("l", "r").agg(F.sort_array(F.collect_set("c")).alias("cands"))


class _Batch:
    """Sides of a batch of sets: ``n`` and ``void`` by set, ``of`` and ``none`` by side, (``cand``, ``side``) and (``case``, ``at``) by member."""

    def __init__(self, batch: pa.RecordBatch, n_tables: int):
        self.n, self.void = (batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("n", "void"))
        sides = batch.column(batch.schema.get_field_index("sides"))
        flat = sides.flatten()
        of = np.repeat(np.arange(len(self.n)), np.diff(sides.offsets.to_numpy()))
        again = flat.field("again").to_numpy(zero_copy_only=False)
        side = np.cumsum(~again) - 1
        self.of, self.none = of[~again], flat.field("none").to_numpy(zero_copy_only=False)[~again]

        def members(name: str) -> tuple[np.ndarray, np.ndarray]:
            lists = flat.field(name)
            return lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.repeat(side, np.diff(lists.offsets.to_numpy()))

        key = members("cands")[1] * n_tables + members("cands")[0] if n_tables else np.zeros(0, np.int64)
        # sides in order, the tables of each in order, none twice; they come nearly so, and a stable sort then takes one run over them
        key = np.sort(key, kind="stable")
        key = key[np.r_[True, key[1:] != key[:-1]]] if len(key) else key
        self.side, self.cand = np.divmod(key, max(n_tables, 1))
        self.case, self.at = members("cases")


def _batches(it: Iterator[pa.RecordBatch], n_tables: int) -> Iterator[_Batch]:
    for batch in it:
        if batch.num_rows:
            yield _Batch(batch, n_tables)


class _Tally:
    """Sums by key."""

    def __init__(self, size: int):
        self.size, self.dense = size, np.zeros(size, np.int64) if size <= DENSE else None
        self.rest: dict[int, int] = defaultdict(int)

    def add(self, keys: np.ndarray, weights: np.ndarray) -> None:
        if self.dense is not None:
            self.dense += np.bincount(keys, weights, self.size).astype(np.int64)
            return
        found, place = np.unique(keys, return_inverse=True)
        for k, w in zip(found.tolist(), np.bincount(place, weights).astype(np.int64).tolist()):
            self.rest[k] += w

    def items(self) -> tuple[np.ndarray, np.ndarray]:
        if self.dense is not None:
            keys = np.flatnonzero(self.dense)
            return keys, self.dense[keys]
        return np.array(list(self.rest), np.int64), np.array(list(self.rest.values()), np.int64)


def _met(tally: _Tally, cand: np.ndarray, group: np.ndarray, weight: np.ndarray, n_tables: int) -> None:
    """Add up ``weight`` (by group) for each two members of a group, whose rows follow each other with tables in order."""
    if not len(cand):
        return
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    length = np.diff(np.r_[starts, len(group)])
    for m in np.unique(length[length > 1]).tolist():
        first = starts[length == m]
        i, j = np.triu_indices(m, 1)
        step = max(1, CHUNK // len(i))
        for k in range(0, len(first), step):
            own = first[k : k + step]
            table = cand[own[:, None] + np.arange(m)]
            tally.add(((table * n_tables)[:, i] + table[:, j]).ravel(), np.repeat(weight[group[own]], len(i)))


def meetings(g: Gathered, keep: np.ndarray | None = None, mode: str = "literal") -> DataFrame:
    """(src, dst, common, clash, lefts, n1, n2) as of :func:`compat.meetings` with the tables' sizes, for the tables marked in ``keep``."""
    if mode not in ("literal", "lenient"):
        raise ValueError(f"unknown mode {mode}")
    n = len(g.tables)
    keep = np.ones(n, bool) if keep is None else keep

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size, agreed, lefts, more, less = (_Tally(k) for k in (n, *4 * (n * n,)))
        for b in _batches(it, n):
            own = keep[b.cand]
            cand, side = b.cand[own], b.side[own]
            weight = b.n[b.of]
            size.add(cand, weight[side])
            of = b.of[side]
            full = ~b.void[of]
            valued = full & ~b.none[side]
            # a table with one side of a left meets every other table there once, at a null right without a clash
            key = of * n + cand
            order = np.argsort(key, kind="stable")
            twice = np.zeros(len(b.n), bool)
            twice[of[order][1:][key[order][1:] == key[order][:-1]]] = True
            odd = np.zeros(len(b.n), bool)
            odd[of[~valued]] = True
            odd |= twice
            plain = order[(full & ~odd[of])[order]]
            _met(lefts, cand[plain], of[plain], b.n, n)
            _met(agreed, cand[valued & ~odd[of]], side[valued & ~odd[of]], weight, n)
            _met(more, cand[valued & odd[of]], side[valued & odd[of]], weight, n)
            for s in np.unique(of[full & odd[of]]).tolist():
                here = slice(*np.searchsorted(of, [s, s + 1]))  # sets stand in order
                held: dict[int, set] = defaultdict(set)
                for c, k in zip(cand[here].tolist(), side[here].tolist()):
                    held[c].add(None if b.none[k] else k)
                names, w, shared, alike = sorted(held), b.n[s], [], []
                for x, a in enumerate(names):
                    for c in names[x + 1 :]:
                        one, two = held[a] - {None}, held[c] - {None}
                        differ = bool(one and two) and (len(one) > 1 or len(two) > 1 or one != two)
                        if mode == "lenient":
                            differ = differ and not one & two
                        shared.append(a * n + c)
                        if not differ:
                            alike.append(a * n + c)
                for tally, keys in ((lefts, shared), (less, alike)):
                    if keys:
                        tally.add(np.array(keys, np.int64), np.full(len(keys), w))
        for kind, tally in enumerate((size, agreed, lefts, more, less)):
            keys, sums = tally.items()
            a, c = (keys, keys) if kind == 0 else np.divmod(keys, max(n, 1))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), kind), pa.int32()), pa.array(a, pa.int32()), pa.array(c, pa.int32()), pa.array(sums, pa.int64())], ["kind", "a", "b", "w"])

    found = stage(g.sets.mapInArrow(run, "kind int, a int, b int, w long").groupBy("kind", "a", "b").agg(F.sum("w").alias("w")), "met")
    # value pairs shared, lefts shared and lefts shared without a clash; the first and the last differ only where a left is odd
    total = lambda *kinds: F.sum(F.when(F.col("kind").isin(*kinds), F.col("w")).otherwise(F.lit(0)))
    both = found.where("kind > 0").groupBy("a", "b").agg(total(1, 3).alias("common"), total(2).alias("lefts"), total(1, 4).alias("agreed"))
    n1, n2 = (found.where("kind = 0").select(F.col("a").alias(side), F.col("w").alias(name)) for side, name in (("a", "n1"), ("b", "n2")))
    name = lambda c: F.element_at(F.array(*[F.lit(t[0]) for t in g.tables]), F.col(c) + 1)
    named = both.join(n1, "a").join(n2, "b").withColumn("x", name("a")).withColumn("y", name("b"))
    turned = lambda a, b: F.when(F.col("x") < F.col("y"), F.col(a)).otherwise(F.col(b))
    return named.select(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst"), "common", (F.col("lefts") - F.col("agreed")).alias("clash"), "lefts", turned("n1", "n2").alias("n1"), turned("n2", "n1").alias("n2"))


def sizes(g: Gathered, labels: dict[str, np.ndarray], resolved: bool = False) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """By name of a labelling: how many value pairs the union of each label's tables has, and how many of them are in each case.

    ``labels``: for each table a number from 0, or -1 for a table left out. ``resolved`` keeps per left only the right that most
    tables of the label hold, among equals the smallest. Results: (pairs by label, pairs by case and label).
    """
    n, n_cases = len(g.tables), len(g.cases)
    alike: dict[bytes, str] = {}
    same = {name: alike.setdefault(np.ascontiguousarray(a, np.int64).tobytes(), name) for name, a in labels.items()}  # equal labellings are counted once
    todo = {name: (np.asarray(labels[name], np.int64), int(max(labels[name], default=-1)) + 1) for name in dict.fromkeys(same.values())}

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = {name: np.zeros((n_cases + 1, k), np.int64) for name, (_, k) in todo.items()}
        for b in _batches(it, n):
            holds = [(c, np.bincount(b.at[b.case == c], minlength=len(b.of)) > 0) for c in np.unique(b.case).tolist()]
            for name, (label, k) in todo.items():
                own = label[b.cand]
                key = b.side[own >= 0] * k + own[own >= 0]
                key, support = np.unique(key, return_counts=True)
                if not len(key):
                    continue
                side, top = np.divmod(key, k)
                if resolved:
                    left = b.of[side] * k + top
                    order = np.lexsort((side, -support, left))
                    first = np.r_[True, left[order][1:] != left[order][:-1]]
                    side, top = side[order][first], top[order][first]
                weight = b.n[b.of[side]]
                sums[name][n_cases] += np.bincount(top, weight, k).astype(np.int64)
                for c, held in holds:
                    hit = held[side]
                    if hit.any():
                        sums[name][c] += np.bincount(top[hit], weight[hit], k).astype(np.int64)
        for name, found in sums.items():
            case, top = np.nonzero(found)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(case), pa.string()), pa.array(case, pa.int32()), pa.array(top, pa.int32()), pa.array(found[case, top], pa.int64())], ["name", "c", "top", "w"])

    out = {name: np.zeros((n_cases + 1, k), np.int64) for name, (_, k) in todo.items()}
    for r in g.sets.mapInArrow(run, "name string, c int, top int, w long").groupBy("name", "c", "top").agg(F.sum("w").alias("w")).toLocalIterator():
        out[r["name"]][r["c"], r["top"]] = r["w"]
    return {name: (out[s][n_cases], out[s][:n_cases]) for name, s in same.items()}


def case_sizes(g: Gathered) -> dict[str, int]:
    """Value pairs of each case; cases without any are left out."""
    return census(g)[1]


def census(g: Gathered) -> tuple[np.ndarray, dict[str, int]]:
    """Value pairs of each table by number, and :func:`case_sizes`, by one pass."""
    n, n_cases = len(g.tables), len(g.cases)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, sums = np.zeros(n, np.int64), np.zeros(n_cases, np.int64)
        for b in _batches(it, n):
            weight = b.n[b.of]
            own += np.bincount(b.cand, weight[b.side], n).astype(np.int64)
            at, case = np.divmod(np.unique(b.at * n_cases + b.case), max(n_cases, 1))
            sums += np.bincount(case, weight[at], n_cases).astype(np.int64)
        k = np.r_[np.arange(n), np.arange(n, n + n_cases)]
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(np.r_[own, sums], pa.int64())], ["k", "w"])

    found = np.zeros(n + n_cases, np.int64)
    for r in g.sets.mapInArrow(run, "k int, w long").groupBy("k").agg(F.sum("w").alias("w")).collect():
        found[r["k"]] = r["w"]
    return found[:n], {c: w for c, w in zip(g.cases, found[n:].tolist()) if w}
