"""Precision, recall and F of relations against ground truth, and the best relation per case."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def prf(relations: DataFrame, truth: DataFrame, n_case: DataFrame | None = None) -> DataFrame:
    """(case_id, relation_id, precision, recall, f) for relations that share a pair with a case.

    ``relations``: distinct (relation_id, l, r); ``truth``: distinct (case_id, l, r); ``n_case``: (case_id, n_case) if known already.
    """
    # merged by hint: both sides hold rows of all tables, whatever the planner thinks
    hit = relations.hint("merge").join(truth, ["l", "r"]).groupBy("case_id", "relation_id").agg(F.count("*").alias("hit"))
    n_rel = relations.groupBy("relation_id").agg(F.count("*").alias("n_rel"))
    n_case = truth.groupBy("case_id").agg(F.count("*").alias("n_case")) if n_case is None else n_case
    full = hit.join(n_rel, "relation_id").join(F.broadcast(n_case), "case_id")
    p, r = F.col("hit") / F.col("n_rel"), F.col("hit") / F.col("n_case")
    return full.select("case_id", "relation_id", p.alias("precision"), r.alias("recall"), (2 * p * r / (p + r)).alias("f"))


def best_relation(scores: DataFrame, by: tuple[str, ...] = ("case_id",)) -> DataFrame:
    """Per case (or ``by``) the relation of best F; ties go to the smaller name."""
    best = F.max_by(F.struct("relation_id", "precision", "recall", "f"), F.struct("f", F.col("precision"))).alias("b")
    first = scores.groupBy(*by, "f", "precision", "recall").agg(F.min("relation_id").alias("relation_id"))
    return first.groupBy(*by).agg(best).select(*by, "b.*")


def summary(best: DataFrame, truth: DataFrame, min_precision: float | None = None) -> DataFrame:
    """Averages over all cases; a case without relation counts 0. ``min_precision`` leaves cases below it out of average precision."""
    cases = truth.select("case_id").distinct().join(best, "case_id", "left").fillna(0.0, ["precision", "recall", "f"])
    good = F.col("precision") if min_precision is None else F.when(F.col("precision") >= min_precision, F.col("precision"))
    return cases.agg(F.avg("f").alias("avg_f"), F.avg(good).alias("avg_precision"), F.avg("recall").alias("avg_recall"))
