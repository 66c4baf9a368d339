"""Step 3: unions of partitions, conflict resolution, expansion by a trusted source."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def union(assign: DataFrame, pairs: DataFrame) -> DataFrame:
    """(cluster_id, l, r, support, domains) of each partition's pairs."""
    full = pairs.join(assign, "cand_id")
    return full.groupBy("cluster_id", "l", "r").agg(F.count_distinct("cand_id").alias("support"), F.count_distinct("domain").alias("domains"))


def majority(united: DataFrame) -> DataFrame:
    """Pairs that iterative removal of the most conflicting occurrence leaves: per left value the right of most support.

    The rarest class always conflicts with most others, so the loop ends at the majority; ties keep the smaller right.
    """
    order = Window.partitionBy("cluster_id", "l").orderBy(F.desc("support"), "r")
    return united.withColumn("k", F.row_number().over(order)).where("k = 1").drop("k")


def _drop_tables(pdf: pd.DataFrame) -> pd.DataFrame:
    left = pdf
    while True:
        rights = left.groupby("l")["r"].transform("nunique")
        n = left[rights > 1].groupby("cand_id").size()
        if n.empty:
            return left[["cluster_id", "cand_id"]].drop_duplicates()
        # most conflicts first; among equals the table with fewest pairs, then the larger id
        sizes = left.groupby("cand_id").size()
        worst = min(n.index, key=lambda c: (-n[c], sizes[c], [-ord(x) for x in c]))
        left = left[left["cand_id"] != worst]


def table_subset(assign: DataFrame, pairs: DataFrame) -> DataFrame:
    """(cluster_id, cand_id) kept when whole tables go, most conflicts first, until none conflicts."""
    full = pairs.join(assign, "cand_id").select("cluster_id", "cand_id", "l", "r")
    return full.groupBy("cluster_id").applyInPandas(_drop_tables, "cluster_id string, cand_id string")


def best_subset(tables: dict[str, set[tuple[str, str]]], max_n: int = 15) -> tuple[set[str], int]:
    """The conflict-free table subset with the largest pair union, by enumeration; among equals the one of most tables, then the first."""
    names = sorted(tables)
    if len(names) > max_n:
        raise ValueError(f"enumeration is for {max_n} tables at most")
    best: tuple[set[str], int] = (set(), -1)
    rank = (-1, -1)
    for bits in range(1 << len(names)):
        chosen = {n for k, n in enumerate(names) if bits >> k & 1}
        pairs = set().union(*(tables[n] for n in chosen)) if chosen else set()
        if len({l for l, _ in pairs}) == len(pairs) and (len(pairs), len(chosen)) > rank:
            best, rank = (chosen, len(pairs)), (len(pairs), len(chosen))
    return best


def best_tables(assign: DataFrame, pairs: DataFrame, max_n: int = 15) -> DataFrame:
    """(cluster_id, cand_id) of the conflict-free tables with the largest union, for clusters of ``max_n`` tables at most; raises beyond."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        chosen, _ = best_subset({c: set(zip(g["l"], g["r"])) for c, g in pdf.groupby("cand_id")}, max_n)
        return pd.DataFrame({"cluster_id": pdf["cluster_id"].iloc[0], "cand_id": sorted(chosen)})

    full = pairs.join(assign, "cand_id").select("cluster_id", "cand_id", "l", "r")
    return full.groupBy("cluster_id").applyInPandas(run, "cluster_id string, cand_id string")


def resolve(assign: DataFrame, pairs: DataFrame, mode: str = "pair") -> DataFrame:
    """Mapping pairs of each cluster: modes pair, table (greedy), exact (best tables of small clusters), none."""
    if mode not in ("pair", "table", "exact", "none"):
        raise ValueError(f"unknown mode {mode}")
    if mode in ("table", "exact"):
        kept = (table_subset if mode == "table" else best_tables)(assign, pairs)
        pairs = pairs.join(kept.select("cand_id"), "cand_id", "left_semi")
    united = union(assign, pairs)
    return united if mode == "none" else majority(united)


def expand(core: DataFrame, trusted: DataFrame, min_containment: float = 0.5, max_conflict: float = 0.2) -> DataFrame:
    """Add the pairs of a trusted source (l, r) to a core (l, r) that it contains well and hardly contradicts."""
    sizes = core.agg(F.count("*").alias("nc")).crossJoin(trusted.agg(F.count("*").alias("nt")))
    agree = core.join(trusted, ["l", "r"]).agg(F.count("*").alias("agree"))
    clash = core.join(trusted.withColumnRenamed("r", "r2"), "l").where("r <> r2").agg(F.count_distinct("l").alias("clash"))
    gate = sizes.crossJoin(agree).crossJoin(clash)  # one row
    good = (F.col("agree") >= min_containment * F.least("nc", "nt")) & (F.col("clash") <= max_conflict * F.least("nc", "nt"))
    new = trusted.join(core, "l", "left_anti").crossJoin(F.broadcast(gate.where(good).select(F.lit(1).alias("one")))).select("l", "r")
    return core.select("l", "r").union(new)
