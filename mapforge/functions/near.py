"""Pairs of values within the fractional edit limit, without comparing all values.

A value of length n has the limit m = min(floor(n f), k). Cut into m + 1 segments, at least one of them
occurs unchanged, moved by m places at most, in any value that m edits can make of it. The shorter value of
a pair sets the limit, so shorter values are indexed by segment, and values of the same length or up to m
longer probe with their substrings at those places. Candidates meet in one equi-join and are then verified.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mapforge.functions import text


def _limit(n: str, f_ed: tuple[int, int], k_ed: int) -> str:
    return f"cast(least({n} * {f_ed[0]} div {f_ed[1]}, {k_ed}) as int)"


def _start(n: str, i: str, m: str) -> str:
    """Where segment i of m + 1 begins: the last ones take the remainder."""
    return f"cast({i} * ({n} div ({m} + 1)) + greatest(0, {i} - ({m} + 1 - {n} % ({m} + 1))) as int)"


def _segments(f_ed: tuple[int, int], k_ed: int) -> Column:
    m = _limit("n", f_ed, k_ed)
    cut = f"struct(n as len, i as at, substring(v, {_start('n', 'i', m)} + 1, {_start('n', '(i + 1)', m)} - {_start('n', 'i', m)}) as part)"
    return F.expr(f"transform(sequence(0, {m}), i -> {cut})")


def _probes(f_ed: tuple[int, int], k_ed: int) -> Column:
    m = _limit("c", f_ed, k_ed)
    size = f"({_start('c', '(i + 1)', m)} - {_start('c', 'i', m)})"
    first, last = f"greatest(0, {_start('c', 'i', m)} - {m})", f"least(n - {size}, {_start('c', 'i', m)} + {m})"
    places = f"if({last} < {first}, array(), transform(sequence({first}, {last}), p -> struct(c as len, i as at, substring(v, p + 1, {size}) as part)))"
    lengths = f"filter(sequence(greatest(1, n - {k_ed}), n), c -> {m} >= 1 and {m} >= n - c)"
    return F.array_distinct(F.expr(f"flatten(transform({lengths}, c -> flatten(transform(sequence(0, {m}), i -> {places}))))"))


def near_values(values: DataFrame, f_ed: tuple[int, int] = (1, 5), k_ed: int = 10, digit_guard: bool = True) -> DataFrame:
    """(a, b) for all unequal values (v) that match approximately, in both orders. Nulls match nothing."""
    own = values.select("v").where("v is not null").distinct().withColumn("n", F.length("v"))
    usable = own.where(f"{_limit('n', f_ed, k_ed)} >= 1")
    index = usable.select(F.col("v").alias("a"), F.explode(_segments(f_ed, k_ed)).alias("s"))
    probe = own.select(F.col("v").alias("b"), F.explode(_probes(f_ed, k_ed)).alias("s"))
    met = index.join(probe, "s").where("a <> b").select("a", "b").distinct()
    good = met.where(text.matches(F.col("a"), F.col("b"), f_ed, k_ed, digit_guard=digit_guard))
    return good.union(good.select("b", "a")).distinct()
