"""Plans that hold at size: no join of rows with rows is planned as a broadcast, and what was rewritten for it equals the plain form."""

from __future__ import annotations

import random
import re

import pytest
from pyspark.sql import functions as F

from mapforge.operators import compat, graph, measures
from mapforge.plans import workloads
from mapforge.sources import corpus

SF = "/root/testdata/sf0.001"


def _value_broadcasts(df) -> list[str]:
    """Broadcast joins by the values of tables; at size their build side is all rows of all tables."""
    return re.findall(r"BroadcastHashJoin \[(?:l|r)#\S*", df._jdf.queryExecution().executedPlan().toString())


@pytest.mark.parametrize("name", ["jaccard_edges", "scale_samples", "overlap_sweep", "edge_sweep", "containment_edges", "pos_edges", "pivot_cc", "positive_cc", "pos_components"])
def test_value_pairs_are_not_broadcast(spark, name):
    assert not _value_broadcasts(workloads.Q[name](spark, SF))


def _plain_shared(pairs):
    a, b = pairs.withColumnRenamed("cand_id", "src"), pairs.withColumnRenamed("cand_id", "dst")
    return a.join(b, ["l", "r"]).where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("common"))


def test_shared_equals_the_plain_join(spark, monkeypatch):
    monkeypatch.setattr(compat, "BLOCK", 3)
    rng = random.Random(2)
    rows = [(f"t{rng.randint(0, 19)}", rng.choice(["a", "b", "", None, "d"]), rng.choice(["x", "y", None])) for _ in range(150)]  # repeated rows too
    pairs = spark.createDataFrame(rows, "cand_id string, l string, r string")
    got = sorted(map(tuple, compat.shared(pairs).collect()))
    assert len(got) > 100 and got == sorted(map(tuple, _plain_shared(pairs).collect()))


def test_sliding_tables_of_any_number_are_distinct_and_whole(spark):
    df = spark.range(70).selectExpr("id as k", "cast(id div 2 as string) as l", "cast(null as string) as r")
    got = [tuple(x) for x in corpus.sliding(df, "k", "l", "r", 65, "q").select("cand_id", "l").collect()]
    want = {(f"q{f:02d}", str(k // 2)) for f in range(65) for k in range(70) if (k - f * 70 // 50) % 70 < 14}
    assert len(got) == len(set(got)) and set(got) == want


@pytest.mark.parametrize("mode", ["literal", "lenient"])
@pytest.mark.parametrize("least", [0, 1, 2])
def test_the_signed_graph_equals_both_weights_apart(spark, monkeypatch, mode, least):
    monkeypatch.setattr(compat, "BLOCK", 3)
    rng = random.Random(least)
    rows = {(f"t{rng.randint(0, 12):02d}", rng.choice(["a", "b", "c", "d", None]), rng.choice(["x", "y", "z", None])) for _ in range(60)}
    rows |= {(f"u{k}", f"m{j}", f"{j * k // 4}") for k in range(8) for j in range(6)}  # each left once in a table
    pairs = spark.createDataFrame(sorted(rows, key=repr), "cand_id string, l string, r string")
    full = compat.positive(pairs, least).join(compat.negative(pairs, mode, least), ["src", "dst"], "full").fillna(0.0)
    got = sorted(map(tuple, compat.signed_graph(pairs, least, mode).collect()))
    assert got == sorted(map(tuple, full.select("src", "dst", "w_pos", "w_neg").collect())) and any(x[3] < 0 for x in got)


def test_the_graph_of_a_chain_broadcasts_no_values(spark):
    """What synth_chain, popularity, positive_cc, pivot_cc and the case queries build on."""
    assert not _value_broadcasts(compat.signed_graph(workloads.chain(spark, SF)))


def test_scores_broadcast_no_values(spark):
    pairs = workloads.chain(spark, SF).select(F.col("cand_id").alias("relation_id"), "l", "r")
    assert not _value_broadcasts(measures.prf(pairs, workloads.truth(spark, SF)))


def test_a_partition_is_a_table_of_known_size(spark):
    """Its join with pairs then never takes the pairs, whose size is underrated, for the smaller side."""
    pairs = workloads.chain(spark, SF)
    edges = spark.createDataFrame([("p00", "p01", 1.0, 0.0)], "src string, dst string, w_pos double, w_neg double")
    assign = graph.synthesize(pairs, edges)
    size = lambda df: int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    assert assign.count() == 50 and size(assign) < size(pairs)


@pytest.mark.parametrize("name", ["cut_one_neg", "cut_two_neg", "exact_small", "relaxed_fivegraph"])
def test_small_graphs_come_from_suppliers(spark, tmp_path, name):
    spark.sql("select * from values (1L, 4), (2L, 4), (3L, 7), (4L, null) t(s_suppkey, s_nationkey)").write.parquet(f"{tmp_path}/supplier.parquet")
    got = {(r[0][0], round(r["loss" if name == "relaxed_fivegraph" else "score"], 6)) for r in workloads.Q[name](spark, str(tmp_path)).collect()}
    one = {"cut_one_neg": 2.77, "cut_two_neg": 2.1, "exact_small": 2.1, "relaxed_fivegraph": 0.6}[name]
    assert got == {("4", round(2 * one, 6)), ("7", one)}


@pytest.mark.parametrize("name", ["case_prf_synthesis", "case_summary_no_neg"])
def test_case_queries_broadcast_no_values(spark, name):
    assert not _value_broadcasts(workloads.Q[name](spark, SF))
