"""Comparison keys and bounded edit matching as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def key(col: Column) -> Column:
    """Lower case without punctuation, spaces and marks."""
    return F.regexp_replace(F.lower(col), r"[^\p{L}\p{N}]+", "")


def limit(a: Column, b: Column, f_ed: tuple[int, int] = (1, 5), k_ed: int = 10) -> Column:
    """Fractional edit limit: the smaller of both floors and of ``k_ed``, in integers."""
    num, den = f_ed
    part = lambda c: F.floor(F.length(c) * num / den).cast("int")
    return F.least(part(a), part(b), F.lit(k_ed))


def digits_equal(a: Column, b: Column) -> Column:
    runs = lambda c: F.trim(F.regexp_replace(c, "[^0-9]+", " "))
    return runs(a) == runs(b)


def matches(a: Column, b: Column, f_ed: tuple[int, int] = (1, 5), k_ed: int = 10, abs_limit: int | None = None, digit_guard: bool = True) -> Column:
    """Edit distance within the limit; lengths and digit runs are compared first, the distance is bounded."""
    most = F.lit(abs_limit) if abs_limit is not None else limit(a, b, f_ed, k_ed)
    near = (F.abs(F.length(a) - F.length(b)) <= most) & (F.call_function("levenshtein", a, b, most) >= 0)
    return (a == b) | ((digits_equal(a, b) if digit_guard else F.lit(True)) & near)


def matches_full(a: Column, b: Column, f_ed: tuple[int, int] = (1, 5), k_ed: int = 10) -> Column:
    """The same test by the full distance; reference for :func:`matches` without guard."""
    return F.levenshtein(a, b) <= limit(a, b, f_ed, k_ed)


def pmi(nu: Column, nv: Column, nuv: Column, n: Column) -> Column:
    return F.log10(nuv * n / (nu * nv))


def npmi(nu: Column, nv: Column, nuv: Column, n: Column) -> Column:
    """PMI over -log of the joint share: 1 where both always meet in all columns, -1 where they never meet."""
    return F.when(nuv == 0, -1.0).when(nuv == n, 1.0).otherwise(pmi(nu, nv, nuv, n) / -F.log10(nuv / n))


def canonicalise(df: DataFrame, col: str, synonyms: DataFrame) -> DataFrame:
    """Replace values of ``col`` by the least member of their synonym group; ``synonyms`` has (a, b)."""
    from mapforge.operators.graph import components

    groups = components(synonyms.select(F.col("a").alias("src"), F.col("b").alias("dst")))
    return df.join(groups.withColumnRenamed("node", col), col, "left").withColumn(col, F.coalesce("comp", col)).select(df.columns)
