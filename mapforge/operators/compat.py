"""Step 2a: positive and negative compatibility through inverted-index joins, exact and approximate.

``pairs`` has (cand_id, l, r) as a set. All scores come from equi-joins on shared values; only
candidates that share something ever meet.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mapforge.functions import text
from mapforge.functions.near import near_values


def sizes(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("cand_id").agg(F.count("*").alias("n"))


def _two_sided(pairs: DataFrame, on: list[str], columns: list[str] | None = None) -> DataFrame:
    a, b = pairs.withColumnRenamed("cand_id", "src"), pairs.withColumnRenamed("cand_id", "dst")
    if on == ["l"] and columns is None:
        a, b = a.withColumnRenamed("r", "r1"), b.withColumnRenamed("r", "r2")
    return a.join(b, on).where("src < dst")


def _with_sizes(counts: DataFrame, pairs: DataFrame) -> DataFrame:
    n = sizes(pairs)
    return counts.join(n.select(F.col("cand_id").alias("src"), F.col("n").alias("n1")), "src").join(n.select(F.col("cand_id").alias("dst"), F.col("n").alias("n2")), "dst")


#: Sets of candidates are met block by block, so no row holds more than two blocks of names.
BLOCK = 100


def _blocks(sets: DataFrame, items: str) -> DataFrame:
    """``sets`` with a row for each two blocks ``x``, ``y`` of the array ``items``, a block met with itself included."""
    cut = F.expr(f"transform(sequence(0, (size({items}) - 1) div {BLOCK}), i -> slice({items}, i * {BLOCK} + 1, {BLOCK}))")
    rest = [c for c in sets.columns if c != items]
    first = sets.select(*rest, cut.alias("cut")).select(*rest, "cut", F.posexplode("cut").alias("i", "x"))
    return first.select(*rest, "x", F.explode(F.expr("slice(cut, i + 1, size(cut))")).alias("y"))


def shared(pairs: DataFrame, theta_overlap: int = 0) -> DataFrame:
    """(src, dst, common): candidates that share more than ``theta_overlap`` value pairs.

    Rows are gathered to the set of candidates that hold a value pair, and equal sets are counted, before candidates meet:
    no join of rows with rows, whose size the planner could underrate.
    """
    rows = pairs.where("cand_id is not null and l is not null and r is not null").select("cand_id", "l", "r")
    held = rows.groupBy("l", "r").agg(F.sort_array(F.collect_list("cand_id")).alias("cands")).where("size(cands) > 1")
    met = _blocks(held.groupBy("cands").agg(F.count("*").alias("n")), "cands")
    met = met.select("n", F.explode("x").alias("src"), "y").select("n", "src", F.explode("y").alias("dst"))
    # within one block each two names meet in both orders, between blocks in one: names are sorted
    counts = met.where("src < dst").groupBy("src", "dst").agg(F.sum("n").alias("common"))
    return counts.where(F.col("common") > theta_overlap)


def jaccard(pairs: DataFrame) -> DataFrame:
    return _with_sizes(shared(pairs), pairs).select("src", "dst", (F.col("common") / (F.col("n1") + F.col("n2") - F.col("common"))).alias("jaccard"))


def containment(pairs: DataFrame) -> DataFrame:
    both = _with_sizes(shared(pairs), pairs)
    return both.select("src", "dst", (F.col("common") / F.col("n1")).alias("containment")).union(both.select(F.col("dst"), F.col("src"), F.col("common") / F.col("n2")))


def positive(pairs: DataFrame, theta_overlap: int = 0) -> DataFrame:
    """(src, dst, w_pos): the larger of both containments."""
    return _with_sizes(shared(pairs, theta_overlap), pairs).select("src", "dst", (F.col("common") / F.least("n1", "n2")).alias("w_pos"))


def positive_all_pairs(pairs: DataFrame) -> DataFrame:
    """Every pair of candidates compared, for small inputs only: the reference for :func:`positive`."""
    pair = F.concat_ws(":", F.length("l"), "l", "r")  # one string for each pair: intersections then go by hash
    sets = pairs.groupBy("cand_id").agg(F.collect_set(pair).alias("s"))
    a, b = sets.select(F.col("cand_id").alias("src"), F.col("s").alias("s1")), sets.select(F.col("cand_id").alias("dst"), F.col("s").alias("s2"))
    met = a.crossJoin(b).where("src < dst").withColumn("common", F.size(F.array_intersect("s1", "s2"))).where("common > 0")
    return met.select("src", "dst", (F.col("common") / F.least(F.size("s1"), F.size("s2"))).alias("w_pos"))


def _keyed(pairs: DataFrame) -> DataFrame:
    return pairs.select("cand_id", text.key(F.col("l")).alias("l"), text.key(F.col("r")).alias("r")).distinct()


def _met_on_left(keyed: DataFrame, f_ed: tuple[int, int], k_ed: int, digit_guard: bool) -> DataFrame:
    """(src, dst, l1, r1, l2, r2) of all rows of two candidates whose lefts match exactly or approximately."""
    lefts = keyed.select(F.col("l").alias("v")).distinct()
    alike = near_values(lefts, f_ed, k_ed, digit_guard).union(lefts.select("v", "v")).toDF("l1", "l2")
    a = keyed.select(F.col("cand_id").alias("src"), F.col("l").alias("l1"), F.col("r").alias("r1"))
    b = keyed.select(F.col("cand_id").alias("dst"), F.col("l").alias("l2"), F.col("r").alias("r2"))
    return a.join(alike, "l1").join(b, "l2").where("src < dst")


def positive_fuzzy(pairs: DataFrame, f_ed: tuple[int, int] = (1, 5), k_ed: int = 10, digit_guard: bool = True) -> DataFrame:
    """w_pos with approximate matches on both sides, none missed: unequal lefts meet by shared segments.

    Exact matches are settled first; edit distances of rights are computed for the rest only.
    """
    keyed = _keyed(pairs)
    exact = _two_sided(keyed, ["l", "r"]).select("src", "dst", "l", "r")
    hits = exact.groupBy("src", "dst").agg(F.count("*").alias("common"))
    near = _met_on_left(keyed, f_ed, k_ed, digit_guard).where("not (l1 = l2 and r1 = r2)")
    near = near.where(text.matches(F.col("r1"), F.col("r2"), f_ed, k_ed, digit_guard=digit_guard))
    near = near.join(exact.select("src", "dst", F.col("l").alias("l1"), F.col("r").alias("r1")), ["src", "dst", "l1", "r1"], "left_anti").join(exact.select("src", "dst", F.col("l").alias("l2"), F.col("r").alias("r2")), ["src", "dst", "l2", "r2"], "left_anti")
    more = near.groupBy("src", "dst").agg(F.least(F.count_distinct("l1", "r1"), F.count_distinct("l2", "r2")).alias("more"))
    both = hits.join(more, ["src", "dst"], "full").select("src", "dst", (F.coalesce("common", F.lit(0)) + F.coalesce("more", F.lit(0))).alias("common"))
    return _with_sizes(both, keyed).select("src", "dst", (F.col("common") / F.least("n1", "n2")).alias("w_pos"))


def conflicts(pairs: DataFrame, mode: str = "literal") -> DataFrame:
    """(src, dst, l): shared left values with unequal rights. ``lenient`` leaves out lefts that also agree."""
    if mode not in ("literal", "lenient"):
        raise ValueError(f"unknown mode {mode}")
    met = _two_sided(pairs.select("cand_id", "l", "r"), ["l"])
    if mode == "lenient":
        return met.groupBy("src", "dst", "l").agg(F.bool_or(F.col("r1") == F.col("r2")).alias("agree")).where("not agree").select("src", "dst", "l")
    return met.where("r1 <> r2").select("src", "dst", "l").distinct()


def negative(pairs: DataFrame, mode: str = "literal", theta_overlap: int = 0) -> DataFrame:
    """(src, dst, w_neg): minus the larger share of conflicting left values, for candidates that share more than ``theta_overlap`` lefts."""
    counts = conflicts(pairs, mode).groupBy("src", "dst").agg(F.count("*").alias("common"))
    if theta_overlap > 0:
        lefts = _two_sided(pairs.select("cand_id", "l").distinct(), ["l"], ["cand_id", "l"]).groupBy("src", "dst").agg(F.count("*").alias("lefts"))
        counts = counts.join(lefts.where(F.col("lefts") > theta_overlap), ["src", "dst"], "left_semi")
    return _with_sizes(counts, pairs).select("src", "dst", (-F.col("common") / F.least("n1", "n2")).alias("w_neg"))


def negative_fuzzy(pairs: DataFrame, f_ed: tuple[int, int] = (1, 5), k_ed: int = 10, digit_guard: bool = True) -> DataFrame:
    """w_neg where lefts that match approximately conflict unless their rights match approximately, so spelling is no conflict."""
    keyed = _keyed(pairs)
    clash = _met_on_left(keyed, f_ed, k_ed, digit_guard).where(~text.matches(F.col("r1"), F.col("r2"), f_ed, k_ed, digit_guard=digit_guard))
    counts = clash.groupBy("src", "dst").agg(F.least(F.count_distinct("l1"), F.count_distinct("l2")).alias("common"))
    return _with_sizes(counts, keyed).select("src", "dst", (-F.col("common") / F.least("n1", "n2")).alias("w_neg"))


def with_synonyms(pairs: DataFrame, synonyms: DataFrame) -> DataFrame:
    """``pairs`` in terms of one name per synonym group on both sides, so all scores and resolution treat synonyms as equal."""
    return text.canonicalise(text.canonicalise(pairs, "l", synonyms), "r", synonyms).distinct()


def _sides(pairs: DataFrame) -> DataFrame:
    """(l, sides): per left value the sets of candidates of each of its rights; ``none`` marks the side of a null right."""
    rows = pairs.where("cand_id is not null and l is not null").select("cand_id", "l", "r")
    held = rows.groupBy("l", "r").agg(F.sort_array(F.collect_list("cand_id")).alias("cands"))
    return held.groupBy("l").agg(F.sort_array(F.collect_list(F.struct("cands", F.isnull("r").alias("none")))).alias("sides"))


def meetings(pairs: DataFrame, mode: str = "literal") -> DataFrame:
    """(src, dst, common, clash, lefts): how many value pairs, conflicting lefts and lefts two candidates share, by one pass.

    Lefts are gathered to their sides and equal ones counted before candidates meet, so no rows are joined with rows.
    """
    if mode not in ("literal", "lenient"):
        raise ValueError(f"unknown mode {mode}")
    equal = _sides(pairs).groupBy("sides").agg(F.count("*").alias("n"))
    equal = equal.withColumn("names", F.flatten("sides.cands")).where("size(names) > 1")
    once = F.size(F.array_distinct("names")) == F.size("names")
    items = F.expr("flatten(transform(sides, (s, k) -> transform(s.cands, c -> struct(c as c, if(s.none, null, k) as k))))")
    laid = equal.withColumn("once", once).select("n", "once", F.when(~once, F.col("sides")).alias("key"), items.alias("items"))
    laid = laid.withColumn("items", F.sort_array("items"))  # by name: a candidate's places stay together
    met = _blocks(laid, "items")
    met = met.select("n", "once", "key", F.explode("x").alias("a"), "y").select("n", "once", "key", "a", F.explode("y").alias("b")).where("a.c < b.c")
    met = met.select("n", "once", "key", F.col("a.c").alias("src"), F.col("b.c").alias("dst"), F.coalesce(F.expr("a.k = b.k"), F.lit(False)).alias("same"), F.coalesce(F.expr("a.k <> b.k"), F.lit(False)).alias("other"))
    total = lambda c: F.sum(F.when(c, F.col("n")).otherwise(F.lit(0)))
    # where each candidate has a left once, counts add up; else two candidates meet at a left more than once and it counts as one left
    plain = met.where("once").groupBy("src", "dst").agg(total(F.col("same")).alias("common"), total(F.col("other")).alias("clash"), F.sum("n").alias("lefts"))
    each = met.where("not once").groupBy("key", "n", "src", "dst").agg((F.count_if("same") * F.first("n")).alias("common"), F.bool_or("other").alias("other"), F.bool_or("same").alias("same"))
    apart = F.col("other") if mode == "literal" else F.col("other") & ~F.col("same")
    rest = each.select("src", "dst", "common", F.when(apart, F.col("n")).otherwise(F.lit(0)).alias("clash"), F.col("n").alias("lefts"))
    return plain.union(rest).groupBy("src", "dst").agg(*[F.sum(c).alias(c) for c in ("common", "clash", "lefts")])


def signed_graph(pairs: DataFrame, theta_overlap: int = 0, mode: str = "literal") -> DataFrame:
    """(src, dst, w_pos, w_neg), 0 where one side is missing."""
    return signed(_with_sizes(meetings(pairs, mode), pairs), theta_overlap)


def signed(both: DataFrame, theta_overlap: int = 0) -> DataFrame:
    """The signed graph from (src, dst, common, clash, lefts, n1, n2)."""
    share = lambda c, kept: F.when(kept, F.col(c) / F.least("n1", "n2")).otherwise(F.lit(0.0))
    agree, differ = F.col("common") > theta_overlap, (F.col("clash") > 0) & (F.col("lefts") > theta_overlap)
    return both.where(agree | differ).select("src", "dst", share("common", agree).alias("w_pos"), F.when(differ, -share("clash", differ)).otherwise(F.lit(0.0)).alias("w_neg"))
