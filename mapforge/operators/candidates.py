"""Step 1: column coherence, ordered column pairs, and functional tests."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mapforge.functions import text
from mapforge.params import SynthParams
from mapforge.sources.storage import stage


def value_counts(cols: DataFrame) -> DataFrame:
    """(value, n): in how many columns each value occurs. ``cols``: distinct (col_uid, value)."""
    return cols.groupBy("value").agg(F.count("*").alias("n"))


def _bounded(cols: DataFrame, max_values: int | None) -> DataFrame:
    if max_values is None:
        return cols
    w = Window.partitionBy("col_uid").orderBy(F.xxhash64("value"), "value")
    return cols.withColumn("k", F.row_number().over(w)).where(F.col("k") <= max_values).drop("k")


def pair_counts(cols: DataFrame, max_values: int | None = None) -> DataFrame:
    """(u, v, n) for values u < v that share a column. ``max_values`` (reported, lossy) bounds values per column."""
    cols = _bounded(cols, max_values)
    a, b = cols.withColumnRenamed("value", "u"), cols.withColumnRenamed("value", "v")
    return a.join(b, "col_uid").where("u < v").groupBy("u", "v").agg(F.count("*").alias("n"))


def pair_scores(cols: DataFrame, score: str = "npmi", exclude_self: bool = False, min_support: int = 1, max_values: int | None = None) -> DataFrame:
    """(u, v, nu, nv, nuv, score). ``exclude_self`` takes one shared column away from every count."""
    total = cols.agg(F.count_distinct("col_uid").alias("total"))
    own = value_counts(cols)
    pairs = pair_counts(cols, max_values).where(F.col("n") >= min_support)
    full = pairs.withColumnRenamed("n", "nuv").join(own.select(F.col("value").alias("u"), F.col("n").alias("nu")), "u").join(own.select(F.col("value").alias("v"), F.col("n").alias("nv")), "v")
    full = full.crossJoin(F.broadcast(total))  # one row
    if exclude_self:
        full = full.select("u", "v", *[(F.col(c) - 1).alias(c) for c in ("nu", "nv", "nuv", "total")])
    fn = text.npmi if score == "npmi" else text.pmi
    return full.select("u", "v", "nu", "nv", "nuv", fn(F.col("nu"), F.col("nv"), F.col("nuv"), F.col("total")).alias("score"))


def column_scores(cols: DataFrame, score: str = "npmi", exclude_self: bool = False, min_support: int = 1, max_values: int | None = None) -> DataFrame:
    """(col_uid, n_pairs, coherence): mean score over unordered value pairs; columns of one value have none.

    Columns are joined with themselves once: counts and scores of value pairs use one dealing of the joined rows.
    """
    total = cols.agg(F.count_distinct("col_uid").alias("total"))
    own = value_counts(cols)
    kept = _bounded(cols, max_values)
    a, b = kept.withColumnRenamed("value", "u"), kept.withColumnRenamed("value", "v")
    met = a.join(b, "col_uid").where("u < v").repartition("u", "v")
    counts = met.groupBy("u", "v").agg(F.count("*").alias("nuv")).where(F.col("nuv") >= min_support)
    full = counts.join(own.select(F.col("value").alias("u"), F.col("n").alias("nu")), "u").join(own.select(F.col("value").alias("v"), F.col("n").alias("nv")), "v").crossJoin(F.broadcast(total))  # one row
    less = F.lit(1 if exclude_self else 0)
    fn = text.npmi if score == "npmi" else text.pmi
    scored = met.join(full, ["u", "v"]).select("col_uid", fn(*[F.col(c) - less for c in ("nu", "nv", "nuv", "total")]).alias("score"))
    return scored.groupBy("col_uid").agg(F.count("*").alias("n_pairs"), F.avg("score").alias("coherence"))


def filter_columns(cols: DataFrame, coherence_min: float, keep_undefined: bool = True) -> DataFrame:
    scores = column_scores(cols)
    low = scores.where(F.col("coherence") < coherence_min)
    kept = cols.join(low, "col_uid", "left_anti")
    return kept if keep_undefined else kept.join(scores, "col_uid", "left_semi")


def column_pairs(cells: DataFrame) -> DataFrame:
    """All ordered column pairs of each table as rows (table_id, domain, l_header, r_header, l, r), one per table row."""
    row = cells.groupBy("table_id", "domain", "row_id").agg(F.collect_list(F.struct("header", "value")).alias("c"))
    left = row.select("table_id", "domain", F.explode("c").alias("x"), "c").select("table_id", "domain", "x", F.explode("c").alias("y"))
    return left.where("x.header <> y.header").select("table_id", "domain", F.col("x.header").alias("l_header"), F.col("y.header").alias("r_header"), F.col("x.value").alias("l"), F.col("y.value").alias("r"))


_CAND = ["table_id", "l_header", "r_header"]


def fd_ratio(pairs: DataFrame, basis: str = "pairs") -> DataFrame:
    """(table_id, l_header, r_header, n_pairs, ratio): the largest functional share of each candidate.

    ``pairs``: the relation as a set; ``rows``: every row counts.
    """
    if basis == "pairs":
        each = pairs.groupBy(*_CAND, "l").agg(F.count_distinct("r").alias("n"))
        return each.groupBy(*_CAND).agg(F.sum("n").alias("n_pairs"), (F.count("*") / F.sum("n")).alias("ratio"))
    each = pairs.groupBy(*_CAND, "l", "r").agg(F.count("*").alias("n")).groupBy(*_CAND, "l").agg(F.max("n").alias("best"), F.sum("n").alias("n"))
    return each.groupBy(*_CAND).agg(F.sum("n").alias("n_pairs"), (F.sum("best") / F.sum("n")).alias("ratio"))


def fd_exact(pairs: DataFrame) -> DataFrame:
    return fd_ratio(pairs).where("ratio = 1.0")


def fd_approx(pairs: DataFrame, theta: float = 0.95, basis: str = "pairs") -> DataFrame:
    return fd_ratio(pairs, basis).where(F.col("ratio") >= theta)


def cardinality(ratios: DataFrame, theta: float = 0.95) -> DataFrame:
    """1:1 where both directions hold, else N:1, for candidates that hold."""
    held = ratios.where(F.col("ratio") >= theta).select(*_CAND)
    back = held.select("table_id", F.col("r_header").alias("l_header"), F.col("l_header").alias("r_header"), F.lit(True).alias("back"))
    return held.join(back, _CAND, "left").select(*_CAND, F.when(F.col("back"), "1:1").otherwise("N:1").alias("cardinality"))


def extract_stats(pairs: DataFrame, theta: float = 0.95) -> DataFrame:
    """Candidates before and after the functional test, and the pruned share."""
    return fd_ratio(pairs).agg(F.count("*").alias("candidates"), F.count_if(F.col("ratio") >= theta).alias("kept")).withColumn("pruned", 1 - F.col("kept") / F.col("candidates"))


def extract(cells: DataFrame, p: SynthParams | None = None, basis: str = "pairs") -> tuple[DataFrame, DataFrame]:
    """Candidates of whole tables, and how many there were: coherent columns, their ordered pairs, those that hold approximately.

    ``cells`` as :func:`mapforge.sources.corpus.melt` makes them. Candidates: distinct (cand_id, domain, table_id, l_header,
    r_header, l, r). Statistics, one row: columns, coherent, candidates (all ordered pairs of all columns), kept, pruned.
    Columns of one value are coherent; without ``coherence_min`` all are.
    """
    p = p or SynthParams()
    uid = F.concat_ws("|", "table_id", "header")
    cols = cells.select(uid.alias("col_uid"), "value").distinct()
    kept = cells.withColumn("col_uid", uid)
    if p.coherence_min is not None:
        low = column_scores(cols).where(F.col("coherence") < p.coherence_min).select("col_uid")
        kept = kept.join(low, "col_uid", "left_anti")
    rows = stage(column_pairs(kept.drop("col_uid")), "column-pairs")
    good = fd_approx(rows, p.theta, basis).select(*_CAND)
    found = rows.join(good, _CAND).withColumn("cand_id", F.concat_ws("|", *_CAND))
    found = stage(found.select("cand_id", "domain", *_CAND, "l", "r").distinct(), "candidates")
    each = lambda df: df.select("table_id", "header").distinct().groupBy("table_id").agg(F.count("*").alias("n"))
    possible = each(cells).agg(F.sum(F.col("n") * (F.col("n") - 1)).alias("candidates"), F.sum("n").alias("columns"))
    stats = possible.crossJoin(each(kept).agg(F.sum("n").alias("coherent"))).crossJoin(found.agg(F.count_distinct("cand_id").alias("kept")))  # one row each
    return found, stats.select("columns", "coherent", "candidates", "kept", (1 - F.col("kept") / F.col("candidates")).alias("pruned"))
