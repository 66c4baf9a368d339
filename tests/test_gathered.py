"""Counted sets give what the tables' rows give: the same graph and the same scores, from fewer rows."""

from __future__ import annotations

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from mapforge.operators import compat, conflicts, gathered, measures
from mapforge.params import SynthParams
from mapforge.plans import experiments
from mapforge.sources import corpus

SF = "/root/testdata/sf0.001"


def _rows(seed: int) -> list[tuple]:
    rng = random.Random(seed)
    rows = {(f"t{rng.randint(0, 12):02d}", rng.choice(["a", "b", "c", "d", "", None]), rng.choice(["x", "y", "z", None])) for _ in range(70)}
    rows |= {(f"u{k}", f"m{j}", f"{j * k // 4}") for k in range(8) for j in range(30)}  # each left once in a table
    return [(c, f"site{int(c[1:]) % 3}", l, r) for c, l, r in sorted(rows, key=repr)]


def _made(spark, seed: int):
    cands = spark.createDataFrame(_rows(seed), "cand_id string, domain string, l string, r string")
    truth = cands.where("l is not null and r is not null and crc32(l) % 3 > 0").select(F.concat(F.lit("C"), F.crc32("r") % 2).alias("case_id"), "l", "r").distinct()
    return cands, truth, gathered.of_tables(cands, truth)


@pytest.mark.parametrize("mode", ["literal", "lenient"])
@pytest.mark.parametrize("dense", [True, False])
def test_the_graph_of_sets_equals_the_graph_of_rows(spark, monkeypatch, mode, dense):
    monkeypatch.setattr(gathered, "DENSE", 1 << 22 if dense else 0)
    cands, _, g = _made(spark, 3)
    for least in (0, 1):
        got = sorted(map(tuple, compat.signed(gathered.meetings(g, mode=mode), least).collect()))
        assert got == sorted(map(tuple, compat.signed_graph(cands, least, mode).collect())) and any(x[3] < 0 for x in got)


def test_a_sample_of_tables_is_compared_alone(spark):
    cands, _, g = _made(spark, 4)
    part = np.array([c < "t06" or c > "u3" for c, _ in g.tables])
    got = sorted(map(tuple, compat.signed(gathered.meetings(g, part)).collect()))
    assert got == sorted(map(tuple, compat.signed_graph(cands.where("cand_id < 't06' or cand_id > 'u3'")).collect())) and got


@pytest.mark.parametrize("resolved", [True, False])
def test_scores_of_sets_equal_scores_of_rows(spark, resolved):
    cands, truth, g = _made(spark, 5)
    assign = {c: f"k{int(c[1:]) % 4}" for c, _ in g.tables if c != "t05"}
    frame = spark.createDataFrame(list(assign.items()), "cand_id string, cluster_id string")
    found = conflicts.resolve(frame, cands, "pair" if resolved else "none").select(F.col("cluster_id").alias("relation_id"), "l", "r").distinct()
    got = experiments.Bench(spark, SF, g, SynthParams()).prf({"": assign}, resolved)
    flat = lambda df: sorted((r[0], r[1], *(round(x, 12) for x in r[2:])) for r in df.collect())
    want = flat(measures.prf(found, truth))
    assert flat(got) == want and len(want) > 4


def test_the_corpus_is_gathered_whole_without_its_rows(spark):
    rows = experiments.web(spark, SF)
    want = {r["cand_id"]: (r["domain"], r["n"]) for r in rows.groupBy("cand_id", "domain").agg(F.count("*").alias("n")).collect()}
    g = experiments.web_sets(spark, SF)
    own = gathered.sizes(g, {"": np.arange(len(g.tables))})[""][0]
    assert {c: (domain, n) for (c, domain), n in zip(g.tables, own.tolist()) if n} == want
    assert g.sets.count() * 10 < sum(n for _, n in want.values())
    degree = {r["case_id"]: r["n"] for r in experiments.truth(spark, SF).groupBy("case_id").agg(F.count("*").alias("n")).collect()}
    assert gathered.case_sizes(g) == degree


def test_samples_have_the_tables_and_edges_of_their_rows(spark):
    cands = experiments.web(spark, SF).where(F.pmod(F.crc32(F.col("cand_id").cast("binary")), F.lit(100)) < 20)
    want = (cands.select("cand_id").distinct().count(), compat.signed_graph(cands, 1).count())
    got = {r["percent"]: (r["n_tables"], r["n_edges"]) for r in experiments.scale_seconds(spark, SF).collect()}
    assert got[20] == want and got[100] > want


def test_all_methods_share_two_passes_over_the_sets(spark, monkeypatch):
    """The matrix has the scores that each method has alone."""
    cands, truth, g = _made(spark, 6)
    b = experiments.Bench(spark, SF, g, SynthParams(theta_edge=0.5))
    known = spark.createDataFrame([("C0", "1|r", 0.5, 0.5, 0.5)], experiments._SCORES)
    monkeypatch.setattr(b, "known", lambda *which: known.where(F.lit(1 in which)))
    flat = lambda df: sorted((r["case_id"], *(round(r[c], 12) for c in ("precision", "recall", "f"))) for r in df.collect())
    alone = {name: flat(score()) for name, score in b.methods().items()}
    passes, sizes = [], gathered.sizes
    monkeypatch.setattr(gathered, "sizes", lambda *a, **k: passes.append(1) or sizes(*a, **k))
    whole = b.matrix().cache()
    assert len(passes) == 2
    assert {name: flat(whole.where(F.col("method") == name)) for name in alone} == alone and len(alone["single_table"]) == 2


def test_a_census_equals_the_rows(spark):
    cands, truth, g = _made(spark, 7)
    own, cases = gathered.census(g)
    assert {c: n for (c, _), n in zip(g.tables, own.tolist())} == {r[0]: r[1] for r in cands.groupBy("cand_id").count().collect()}
    assert cases == {r[0]: r[1] for r in truth.groupBy("case_id").count().collect()}


@pytest.mark.parametrize("name, passes", [("tau_quality", 1), ("overlap_quality", 1)])
def test_a_sweep_is_scored_by_one_pass(spark, monkeypatch, name, passes):
    seen, sizes = [], gathered.sizes
    monkeypatch.setattr(experiments, "web_sets", lambda s, d: _made(s, 8)[2])
    monkeypatch.setattr(gathered, "sizes", lambda *a, **k: seen.append(1) or sizes(*a, **k))
    assert len(experiments.Q[name](spark, SF).collect()) == 5 and len(seen) == passes


def test_samples_are_counted_once_beside_their_scores(spark, monkeypatch):
    seen, sizes = [], gathered.sizes
    monkeypatch.setattr(experiments, "web_sets", lambda s, d: _made(s, 9)[2])
    monkeypatch.setattr(gathered, "sizes", lambda *a, **k: seen.append(1) or sizes(*a, **k))
    assert len(experiments.scale_seconds(spark, SF).collect()) == len(seen) == 5


@pytest.mark.parametrize("n", [1, 7, 60, 65, 130])
def test_numbers_come_out_of_their_bits_in_compiled_code(spark, n):
    """A lambda for each number of each value pair took one task 19 s for 1.2 million pairs."""
    rng = random.Random(n)
    rows = [(rng.choice(["a", "b", None]), rng.randrange(n)) for _ in range(150)]
    got = corpus.marked(spark.createDataFrame(rows, "k string, f int"), ["k"], n, first=3)
    assert "lambda" not in got._jdf.queryExecution().executedPlan().toString().lower()
    assert {r["k"]: r["fs"] for r in got.collect()} == {k: sorted({f + 3 for x, f in rows if x == k}) for k in {x for x, _ in rows}}


def test_members_stand_in_order_and_once(spark):
    sides = [{"cands": [2, 5], "cases": [], "again": False, "none": False}, {"cands": [0, 2], "cases": [1], "again": True, "none": False}, {"cands": [1], "cases": [0], "again": False, "none": True}]
    frame = spark.createDataFrame([(4, False, sides), (2, True, [])], "n long, void boolean, sides array<struct<cands:array<int>,cases:array<int>,again:boolean,none:boolean>>")
    b = gathered._Batch(frame.toArrow().combine_chunks().to_batches()[0], 6)
    assert (b.side.tolist(), b.cand.tolist()) == ([0, 0, 0, 1], [0, 2, 5, 1]) and (b.case.tolist(), b.at.tolist()) == ([1, 0], [0, 1])
