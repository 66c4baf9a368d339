"""Table corpora: melting wide tables to cells, and the cutters that make partial tables of a relation."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def melt(df: DataFrame, table_id: Column, domain: Column, row_id: Column, columns: list[str]) -> DataFrame:
    """One row per non-null cell: (table_id, domain, row_id, col_id, header, value). No shuffle."""
    cells = F.array(*[F.struct(F.lit(k).alias("col_id"), F.lit(c).alias("header"), F.col(c).cast("string").alias("value")) for k, c in enumerate(columns)])
    wide = df.select(table_id.cast("string").alias("table_id"), domain.cast("string").alias("domain"), row_id.cast("long").alias("row_id"), F.explode(cells).alias("c"))
    return wide.select("table_id", "domain", "row_id", "c.*").where("value is not null")


def sliding(df: DataFrame, key: str, left: str, right: str, fragments: int, name: str, steps: int = 50, width: int = 5) -> DataFrame:
    """Fragments f of a relation: keys k with pmod(k - f n / steps, n) < n / width, n the relation's size.

    Few fragments make a chain of overlapping tables, ``steps`` of them a ring. Columns: cand_id, domain, l, r.
    """
    cut = windows(df, key, left, right, fragments, steps, width).withColumn("f", F.explode("fs"))
    cand = F.concat(F.lit(f"{name}"), F.lpad(F.col("f").cast("string"), 2, "0"))
    return cut.select(cand.alias("cand_id"), F.concat(F.lit("site"), F.pmod("f", F.lit(12)).cast("string")).alias("domain"), "l", "r")


def windows(df: DataFrame, key: str, left: str, right: str, fragments: int, steps: int = 50, width: int = 5, first: int = 0) -> DataFrame:
    """(l, r, fs): distinct value pairs of a relation with the numbers, from ``first``, of the fragments of :func:`sliding` that hold them."""
    n = df.count()
    near = F.pmod(F.col("key") - F.floor(F.col("f") * n / steps).cast("long"), F.lit(n)) < n // width
    rows = df.select(F.col(key).alias("key"), F.col(left).cast("string").alias("l"), F.col(right).cast("string").alias("r"))
    return marked(rows.withColumn("f", F.explode(F.sequence(F.lit(0), F.lit(fragments - 1)))).where(near), ["l", "r"], fragments, first)


def marked(rows: DataFrame, by: list[str], n: int, first: int = 0) -> DataFrame:
    """(``by``, fs): the distinct numbers ``f``, from 0 below ``n``, of each group's rows, each raised by ``first``."""
    word = 60
    # numbers are gathered as bits, so groups are shuffled once
    bits = [F.bit_or(F.expr(f"if(f div {word} = {k}, shiftleft(1L, f % {word}), 0L)")).alias(f"w{k}") for k in range(-(-n // word))]
    # read again piece by piece from tables of what its bits stand for: a lambda would be run for each number outside the compiled code
    piece = 6
    read = []
    for low in range(0, n, piece):
        known = [[low + j + first for j in range(min(piece, n - low)) if m >> j & 1] for m in range(1 << piece)]
        at = F.shiftright(f"w{low // word}", low % word).bitwiseAND(F.lit((1 << piece) - 1)).cast("int")
        read.append(F.get(F.from_json(F.lit(json.dumps(known)), "array<array<int>>"), at))
    return rows.groupBy(*by).agg(*bits).select(*by, F.concat(*read).alias("fs"))


def codes(nation: DataFrame) -> DataFrame:
    """Two standards for the same names, two copies of the first, and a bridge that fits both."""
    a, even = F.concat(F.lit("C"), F.col("n_nationkey")), F.pmod("n_nationkey", F.lit(2)) == 0
    b = F.when(even, a).otherwise(F.concat(F.lit("D"), F.col("n_nationkey")))
    rows = [("A1", a, F.lit(True)), ("A2", a, F.lit(True)), ("B", b, F.lit(True)), ("AB", a, even)]
    parts = [nation.where(keep).select(F.lit(c).alias("cand_id"), F.lit(f"site{k}").alias("domain"), F.col("n_name").alias("l"), r.alias("r")) for k, (c, r, keep) in enumerate(rows)]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def dirty(pairs: DataFrame, every: int = 97) -> DataFrame:
    """Odd fragments get a wrong right value for keys divisible by ``every``."""
    wrong = (F.pmod(F.col("l").cast("long"), F.lit(every)) == 0) & (F.pmod(F.substring("cand_id", -2, 2).cast("int"), F.lit(4)) == 1)
    return pairs.withColumn("r", F.when(wrong, F.lit("Brand#WRONG")).otherwise(F.col("r")))


def nav_cells(pages: DataFrame) -> DataFrame:
    """Navigation lists of pages as one-column tables."""
    items = F.regexp_extract_all("html", F.lit("<li>(?:<a[^>]*>)?([^<]+)"), F.lit(1))
    return pages.select(F.col("page_id").cast("string").alias("col_uid"), F.explode(items).alias("value")).distinct()


def triples(spark: SparkSession, sf_dir: str, which: int = 1) -> DataFrame:
    """Subject, predicate, object rows of two knowledge bases of different coverage."""
    nation, region = read(spark, sf_dir, "nation"), read(spark, sf_dir, "region")
    named = nation.join(region, nation.n_regionkey == region.r_regionkey)
    t = named.select(F.col("n_name").alias("s"), F.lit("in_region").alias("p"), F.col("r_name").alias("o"))
    if which == 2:
        return t.union(nation.select(F.col("n_name"), F.lit("code"), F.col("n_nationkey").cast("string")))
    cust = read(spark, sf_dir, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    part = read(spark, sf_dir, "part")
    return t.union(cust.select("c_name", F.lit("of_nation"), "n_name")).union(part.select(F.col("p_partkey").cast("string"), F.lit("brand"), "p_brand"))
