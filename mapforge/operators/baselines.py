"""Alternatives to synthesis: header unions, thresholded components, pivot clustering, single tables, knowledge bases, form matching."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mapforge.functions.near import near_values
from mapforge.operators.graph import components, synthesize, thinned
from mapforge.params import SynthParams
from mapforge.sources.storage import stage


def header_union(cands: DataFrame, scope: str = "domain", rows: DataFrame | None = None) -> DataFrame:
    """(cand_id, cluster_id): candidates of equal headers, within a domain or over the whole corpus.

    With ``rows`` (cand_id, l, r), only candidates whose rows are disjoint from those of all others of equal headers (and domain)
    are united; one that shares a row with another stays alone.
    """
    if scope not in ("domain", "corpus"):
        raise ValueError(f"unknown scope {scope}")
    parts = (["domain"] if scope == "domain" else []) + ["l_header", "r_header"]
    named = cands.select("cand_id", F.concat_ws("|", *parts).alias("cluster_id")).distinct()
    if rows is None:
        return named
    held = rows.select("cand_id", "l", "r").distinct().join(named, "cand_id").groupBy("cluster_id", "l", "r").agg(F.count("*").alias("n"), F.collect_list("cand_id").alias("cands"))
    return _part(named, held.where("n > 1").select(F.explode("cands").alias("cand_id")))


def header_union_disjoint(cands: DataFrame, shared: DataFrame, scope: str = "domain") -> DataFrame:
    """:func:`header_union` of disjoint rows, from the pairs (src, dst) of candidates that share a row."""
    named = header_union(cands, scope)
    a, b = (named.select(F.col("cand_id").alias(end), F.col("cluster_id").alias(c)) for end, c in (("src", "c1"), ("dst", "c2")))
    met = shared.join(a, "src").join(b, "dst").where("c1 = c2")
    return _part(named, met.select(F.col("src").alias("cand_id")).union(met.select("dst")))


def _part(named: DataFrame, sharing: DataFrame) -> DataFrame:
    shared = sharing.distinct().withColumn("alone", F.lit(True))
    return named.join(shared, "cand_id", "left").select("cand_id", F.when(F.col("alone"), F.col("cand_id")).otherwise(F.col("cluster_id")).alias("cluster_id"))


def signed_components(nodes: DataFrame, edges: DataFrame, alpha: float = 0.5, cut: float = 0.4) -> DataFrame:
    """Components over edges whose weighted mix of both scores reaches ``cut``."""
    kept = edges.where(alpha * F.col("w_pos") + (1 - alpha) * F.col("w_neg") >= cut)
    comp = components(kept).select(F.col("node").alias("cand_id"), F.col("comp").alias("cluster_id"))
    return nodes.select("cand_id").distinct().join(comp, "cand_id", "left").select("cand_id", F.coalesce("cluster_id", "cand_id").alias("cluster_id"))


def positive_components(nodes: DataFrame, edges: DataFrame, cut: float = 0.5) -> DataFrame:
    return signed_components(nodes, edges, 1.0, cut)


def component_sweep(nodes: DataFrame, edges: DataFrame, alpha: float = 0.5, cuts: tuple[float, ...] = tuple(k / 10 for k in range(11))) -> DataFrame:
    """(cut, cand_id, cluster_id): :func:`signed_components` for every cut, by one run over one graph for each of them side by side."""
    return component_sweeps(nodes, edges, (alpha,), cuts).drop("alpha")


def component_sweeps(nodes: DataFrame, edges: DataFrame, alphas: tuple[float, ...], cuts: tuple[float, ...] = tuple(k / 10 for k in range(11))) -> DataFrame:
    """(alpha, cut, cand_id, cluster_id): :func:`component_sweep` for every alpha, in the same run.

    Cuts share most edges, and what joins two nodes more than once is left out before the graphs are divided.
    """
    grid = lambda df: df.withColumn("alpha", F.explode(F.array(*map(F.lit, alphas)))).withColumn("cut", F.explode(F.array(*map(F.lit, cuts))))
    weight = F.col("alpha") * F.col("w_pos") + (1 - F.col("alpha")) * F.col("w_neg")
    kept = grid(edges).where((weight >= F.col("cut")) & (weight > 0))
    name = lambda c: F.concat(F.format_string("%.3f|%.3f|", "alpha", "cut"), F.col(c))
    comp = components(thinned(kept.select(name("src").alias("src"), name("dst").alias("dst"))))
    every = grid(nodes.select("cand_id").distinct()).withColumn("node", name("cand_id"))
    found = every.join(comp, "node", "left")
    return found.select("alpha", "cut", "cand_id", F.coalesce(F.expr("substring(comp, 13)"), F.col("cand_id")).alias("cluster_id"))


def pivot_clusters(nodes: DataFrame, edges: DataFrame, seed: int = 1, max_rounds: int = 50) -> DataFrame:
    """Parallel pivots: vertices first among their neighbours by a hash take their positive neighbours, round by round.

    ``max_rounds`` stands for a time limit; what is left then stays alone. Adds ``round``, for counts of rounds.
    """
    good = edges.where(F.col("w_pos") + F.col("w_neg") > 0).select("src", "dst")
    both = stage(good.union(good.select(F.col("dst"), F.col("src"))), "pivot")
    left = nodes.select("cand_id").distinct().withColumn("rank", F.xxhash64(F.lit(seed), "cand_id"))
    done = None
    for k in range(max_rounds):
        left = stage(left, "pivot")
        if left.isEmpty():
            break
        a = left.select(F.col("cand_id").alias("src"), F.col("rank").alias("r1"))
        b = left.select(F.col("cand_id").alias("dst"), F.col("rank").alias("r2"))
        live = both.join(a, "src").join(b, "dst")
        beaten = live.where("r2 < r1 or (r2 = r1 and dst < src)").select("src").distinct()
        pivots = left.join(beaten.withColumnRenamed("src", "cand_id"), "cand_id", "left_anti").select(F.col("cand_id").alias("src"), "rank")
        taken = live.select("src", "dst").join(pivots, "src").groupBy("dst").agg(F.min_by("src", "rank").alias("cluster_id")).withColumnRenamed("dst", "cand_id")
        got = stage(pivots.select(F.col("src").alias("cand_id"), F.col("src").alias("cluster_id")).union(taken).withColumn("round", F.lit(k + 1)), "pivot")
        done = got if done is None else done.union(got)
        left = left.join(got, "cand_id", "left_anti")
    rest = left.select("cand_id", F.col("cand_id").alias("cluster_id"), F.lit(max_rounds).alias("round"))
    return rest if done is None else done.union(rest)


def form_matcher(nodes: DataFrame, cands: DataFrame, sim_min: float = 0.5, f_ed: tuple[int, int] = (1, 4), k_ed: int = 3) -> DataFrame:
    """Header similarity with equal value types, greedily clustered. ``cands``: (cand_id, l_header, r_header, l_type, r_type).

    Similarity is the larger of the shared words' part of all words and of one minus the edit distance's part of the length.
    Candidates meet when their headers share a word, exactly or within the edit limit; those of equal headers and types are one unit.
    """
    unit = stage(cands.groupBy("l_header", "r_header", "l_type", "r_type").agg(F.min("cand_id").alias("cand_id")), "headers")
    said = F.lower(F.concat_ws(" ", "l_header", "r_header"))
    tagged = unit.select("cand_id", "l_type", "r_type", said.alias("h"), F.array_distinct(F.split(said, "[^a-z0-9]+")).alias("w")).withColumn("word", F.explode("w"))
    words = tagged.select(F.col("word").alias("v")).distinct()
    alike = near_values(words, f_ed, k_ed).union(words.select("v", "v")).toDF("word", "other")
    a = tagged.select(F.col("cand_id").alias("src"), "l_type", "r_type", "word", F.col("h").alias("h1"), F.col("w").alias("w1"))
    b = tagged.select(F.col("cand_id").alias("dst"), "l_type", "r_type", F.col("word").alias("other"), F.col("h").alias("h2"), F.col("w").alias("w2"))
    met = a.join(alike, "word").join(b, ["l_type", "r_type", "other"]).where("src < dst").select("src", "dst", "h1", "h2", "w1", "w2").distinct()
    tokens = F.size(F.array_intersect("w1", "w2")) / F.size(F.array_union("w1", "w2"))
    edit = 1 - F.levenshtein("h1", "h2") / F.greatest(F.length("h1"), F.length("h2"))
    edges = met.select("src", "dst", F.greatest(tokens, edit).alias("w_pos"), F.lit(0.0).alias("w_neg")).where(F.col("w_pos") >= sim_min)
    got = synthesize(unit, edges, SynthParams(theta_edge=sim_min, use_negative=False)).withColumnRenamed("cand_id", "unit_id")
    named = cands.join(unit.withColumnRenamed("cand_id", "unit_id"), ["l_header", "r_header", "l_type", "r_type"])
    return named.join(got, "unit_id").select("cand_id", "cluster_id")


def kb_relations(triples: DataFrame) -> DataFrame:
    """(relation_id, l, r): triples by predicate, in both directions."""
    there = triples.select(F.col("p").alias("relation_id"), F.col("s").alias("l"), F.col("o").alias("r"))
    back = triples.select(F.concat("p", F.lit("~")), F.col("o"), F.col("s"))
    return there.union(back).distinct()
