"""Curation, lookup and the consumers of mappings: correction, filling, joining."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def popularity(assign: DataFrame, pairs: DataFrame) -> DataFrame:
    """(cluster_id, n_domains, n_tables)."""
    cands = pairs.select("cand_id", "domain").distinct()
    return assign.join(cands, "cand_id").groupBy("cluster_id").agg(F.count_distinct("domain").alias("n_domains"), F.count_distinct("cand_id").alias("n_tables"))


def popular(stats: DataFrame, min_domains: int = 8, k: int | None = None) -> DataFrame:
    kept = stats.where(F.col("n_domains") >= min_domains)
    return kept if k is None else kept.orderBy(F.desc("n_domains"), F.desc("n_tables"), "cluster_id").limit(k)


def drop_numeric_temporal(mapping: DataFrame, most: float = 0.9) -> DataFrame:
    """Clusters whose left or right values are mostly numbers or times are left out."""
    plain = lambda c: F.avg(F.col(c).rlike(r"^[-+]?[0-9]+(?:[.,][0-9]+)*$|^[0-9]{4}-[0-9]{2}-[0-9]{2}").cast("double"))
    bad = mapping.groupBy("cluster_id").agg(plain("l").alias("nl"), plain("r").alias("nr")).where(f"nl > {most} or nr > {most}")
    return mapping.join(bad, "cluster_id", "left_anti")


def overlaps(mapping: DataFrame) -> DataFrame:
    """(c1, c2, n): clusters that share left values."""
    a, b = mapping.select(F.col("cluster_id").alias("c1"), "l").distinct(), mapping.select(F.col("cluster_id").alias("c2"), "l").distinct()
    return a.join(b, "l").where("c1 < c2").groupBy("c1", "c2").agg(F.count("*").alias("n"))


def diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """(l, r, change): pairs that came or went between two runs."""
    a, b = old.select("l", "r").distinct(), new.select("l", "r").distinct()
    return b.join(a, ["l", "r"], "left_anti").withColumn("change", F.lit("added")).union(a.join(b, ["l", "r"], "left_anti").withColumn("change", F.lit("removed")))


def index(mapping: DataFrame) -> DataFrame:
    """Hash table of both sides: (h, cluster_id, side)."""
    both = mapping.select("cluster_id", F.explode(F.array(F.struct(F.lit("l").alias("side"), F.col("l").alias("v")), F.struct(F.lit("r").alias("side"), F.col("r").alias("v")))).alias("x"))
    return both.select(F.xxhash64("x.v").alias("h"), "x.v", "cluster_id", "x.side").distinct()


def lookup(values: DataFrame, indexed: DataFrame, min_containment: float = 0.5) -> DataFrame:
    """(cluster_id, side, containment) of mappings that hold enough of ``values`` (v)."""
    asked = values.select("v").distinct()
    n = asked.agg(F.count("*").alias("n"))
    hits = asked.withColumn("h", F.xxhash64("v")).join(indexed, ["h", "v"]).groupBy("cluster_id", "side").agg(F.count("*").alias("hit"))
    return hits.crossJoin(F.broadcast(n)).select("cluster_id", "side", (F.col("hit") / F.col("n")).alias("containment")).where(F.col("containment") >= min_containment)


BITS = 4096 * 8


def index_bits(indexed: DataFrame) -> DataFrame:
    """(cluster_id, side, bits): one bitmap of ``BITS`` hashed places for each mapping side, a filter before :func:`lookup`."""
    return indexed.groupBy("cluster_id", "side").agg(F.bitmap_construct_agg(F.pmod("h", F.lit(BITS)).cast("int")).alias("bits"))


def lookup_filtered(values: DataFrame, indexed: DataFrame, bits: DataFrame, min_containment: float = 0.5, most: int = 10_000) -> DataFrame:
    """As :func:`lookup`, but mappings whose bitmap lacks too many of the values' places never meet them.

    The places of the values travel as one row; for more than ``most`` values the bitmaps say little and all mappings are looked up.
    """
    asked = values.select(F.xxhash64("v").alias("h")).distinct()
    n = asked.count()
    if n > most:
        return lookup(values, indexed, min_containment)
    places = asked.agg(F.collect_list(F.pmod("h", F.lit(BITS)).cast("int")).alias("places"))
    hit = F.expr("size(filter(places, p -> (conv(hex(substring(bits, p div 8 + 1, 1)), 16, 10) div cast(power(2, p % 8) as int)) % 2 = 1))")
    near = bits.crossJoin(F.broadcast(places)).where(hit >= min_containment * n).select("cluster_id", "side")  # one row of places
    return lookup(values, indexed.join(near, ["cluster_id", "side"], "left_semi"), min_containment)


def auto_correct(df: DataFrame, col: str, mapping: DataFrame) -> DataFrame:
    """``df`` with ``suggested``: where a column mixes both sides of a mapping, the rarer side is put in terms of the other."""
    m = mapping.select("l", "r").distinct()
    ends = df.join(m.select(F.col("l").alias(col), F.col("r").alias("to_r")), col, "left").join(m.groupBy("r").agg(F.min("l").alias("to_l")).withColumnRenamed("r", col), col, "left")
    share = ends.agg(F.count("to_r").alias("lefts"), F.count("to_l").alias("rights"))
    full = ends.crossJoin(F.broadcast(share))  # one row
    fix = F.when((F.col("lefts") >= F.col("rights")) & F.col("to_l").isNotNull() & F.col("to_r").isNull(), F.col("to_l")).when((F.col("lefts") < F.col("rights")) & F.col("to_r").isNotNull() & F.col("to_l").isNull(), F.col("to_r"))
    return full.select(*df.columns, F.coalesce(fix, F.col(col)).alias("suggested"))


def auto_fill(df: DataFrame, key: str, examples: DataFrame, mappings: DataFrame) -> DataFrame:
    """``df`` with ``filled`` from the mapping that agrees with most examples (l, r)."""
    hits = examples.join(mappings, ["l", "r"]).groupBy("cluster_id").agg(F.count("*").alias("n"))
    best = hits.agg(F.max_by("cluster_id", F.struct("n", F.col("cluster_id"))).alias("cluster_id"))
    chosen = mappings.join(F.broadcast(best), "cluster_id").groupBy("l").agg(F.min("r").alias("filled"))
    return df.join(chosen.withColumnRenamed("l", key), key, "left").select(*df.columns, "filled")


def auto_join(a: DataFrame, a_key: str, b: DataFrame, b_key: str, mapping: DataFrame) -> DataFrame:
    """``a`` and ``b`` joined through a mapping from a's keys to b's."""
    bridge = mapping.select(F.col("l").alias("__l"), F.col("r").alias("__r")).distinct()
    return a.join(bridge, a[a_key] == F.col("__l")).join(b, F.col("__r") == b[b_key]).drop("__l", "__r")


def search_tables(values: DataFrame, pairs: DataFrame, k: int = 10) -> DataFrame:
    """Raw tables ranked by how many of ``values`` (v) their left column holds."""
    n = values.select("v").distinct()
    return pairs.select("cand_id", F.col("l").alias("v")).distinct().join(n, "v").groupBy("cand_id").agg(F.count("*").alias("hit")).orderBy(F.desc("hit"), "cand_id").limit(k)
