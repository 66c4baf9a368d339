"""Baselines, extraction and the method comparison against brute force in plain Python."""

from __future__ import annotations

import itertools
import random

import pytest
from pyspark.sql import functions as F

from mapforge.operators import apps, baselines, candidates, compat, conflicts, exact, graph
from mapforge.params import SynthParams
from mapforge.plans import experiments, workloads
from mapforge.sources import corpus

SF = "/root/testdata/sf0.001"


def _edges(rng: random.Random, nodes: list[str]) -> list[tuple[str, str, float, float]]:
    return [(a, b, round(rng.choice([0.0, 0.0, 0.3, 0.6, 0.9]), 2), rng.choice([0.0, 0.0, 0.0, -0.5])) for a, b in itertools.combinations(nodes, 2)]


EDGE = "src string, dst string, w_pos double, w_neg double"


def test_pivots_equal_a_simulation(spark):
    rng = random.Random(2)
    names = [f"v{k:02}" for k in range(25)]
    edges = [e for e in _edges(rng, names) if rng.random() < 0.3]
    nodes = spark.createDataFrame([(n,) for n in names], "cand_id string")
    rank = {r["cand_id"]: r["h"] for r in nodes.select("cand_id", F.xxhash64(F.lit(1), "cand_id").alias("h")).collect()}
    near = {n: set() for n in names}
    for a, b, pos, neg in edges:
        if pos + neg > 0:
            near[a].add(b)
            near[b].add(a)
    want, left, k = {}, set(names), 0
    while left:
        k += 1
        pivots = [n for n in left if all((rank[n], n) < (rank[m], m) for m in near[n] & left)]
        taken = {m: min((p for p in pivots if m in near[p]), key=lambda p: rank[p]) for p in pivots for m in near[p] & left}
        want |= {p: (p, k) for p in pivots} | {m: (p, k) for m, p in taken.items()}
        left -= set(pivots) | set(taken)
    got = {r["cand_id"]: (r["cluster_id"], r["round"]) for r in baselines.pivot_clusters(nodes, spark.createDataFrame(edges, EDGE)).collect()}
    assert got == want and k > 1


def test_pivots_stop_at_their_limit(spark):
    names = [f"v{k}" for k in range(12)]
    chain = [(a, b, 0.9, 0.0) for a, b in itertools.pairwise(names)]
    got = baselines.pivot_clusters(spark.createDataFrame([(n,) for n in names], "cand_id string"), spark.createDataFrame(chain, EDGE), max_rounds=1).collect()
    assert sorted(r["cand_id"] for r in got) == sorted(names)


def test_component_sweep_equals_single_cuts(spark):
    names = [f"v{k}" for k in range(14)]
    nodes = spark.createDataFrame([(n,) for n in names], "cand_id string")
    edges = spark.createDataFrame([e for e in _edges(random.Random(5), names) if random.Random(str(e)).random() < 0.2], EDGE)
    sweep = baselines.component_sweep(nodes, edges, 0.5, (0.1, 0.3, 0.45)).collect()
    for cut in (0.1, 0.3, 0.45):
        one = {(r["cand_id"], r["cluster_id"]) for r in baselines.signed_components(nodes, edges, 0.5, cut).collect()}
        assert {(r["cand_id"], r["cluster_id"]) for r in sweep if r["cut"] == cut} == one


def test_sweeps_side_by_side_equal_single_sweeps_and_need_no_rounds(spark, monkeypatch):
    """More edges than are solved in one task, but few nodes: what is left after thinning is solved in one."""
    names = [f"v{k:02d}" for k in range(40)]
    nodes = spark.createDataFrame([(n,) for n in names], "cand_id string")
    edges = spark.createDataFrame([e for e in _edges(random.Random(6), names) if random.Random(str(e)).random() < 0.5], EDGE).coalesce(1)
    want = {a: sorted(map(tuple, baselines.component_sweep(nodes, edges, a, (0.2, 0.6)).collect())) for a in (0.5, 1.0)}
    limited = lambda e: graph.components(e, max_rounds=0, local_edges=4 * len(names))
    monkeypatch.setattr(baselines, "components", limited)
    assert edges.where("w_pos > 0.2").count() > 4 * len(names)
    sweeps = baselines.component_sweeps(nodes, edges, (0.5, 1.0), (0.2, 0.6)).collect()
    assert {a: sorted(tuple(r)[1:] for r in sweeps if r["alpha"] == a) for a in want} == want


def test_form_matcher_meets_misspelt_headers(spark):
    rows = [("a", "country name", "code"), ("b", "country nane", "code"), ("c", "countrey name", "code"), ("d", "price", "amount"), ("e", "country name", "amount")]
    cands = spark.createDataFrame([(c, l, r, "string", "int" if c == "e" else "string") for c, l, r in rows], "cand_id string, l_header string, r_header string, l_type string, r_type string")
    got = {r["cand_id"]: r["cluster_id"] for r in baselines.form_matcher(cands, cands, 0.7).collect()}
    assert got["a"] == got["b"] == got["c"] and len({got["a"], got["d"], got["e"]}) == 3


def test_header_unions_of_disjoint_rows(spark):
    cands = spark.createDataFrame([("a", "d", "x", "y"), ("b", "d", "x", "y"), ("c", "d", "x", "y")], "cand_id string, domain string, l_header string, r_header string")
    rows = spark.createDataFrame([("a", "1", "2"), ("b", "1", "2"), ("c", "3", "4")], "cand_id string, l string, r string")
    got = {r["cand_id"]: r["cluster_id"] for r in baselines.header_union(cands, "domain", rows).collect()}
    assert got == {"a": "a", "b": "b", "c": "d|x|y"}
    with pytest.raises(ValueError):
        baselines.header_union(cands, "galaxy")


def test_overlap_limits_both_weights(spark):
    rows = [(c, f"l{k}", f"r{k}" if c == "a" or k % 2 else "other") for c in "ab" for k in range(6)]
    pairs = spark.createDataFrame(rows, "cand_id string, l string, r string")
    for most, n_pos, n_neg in ((0, 1, 1), (2, 1, 1), (3, 0, 1), (6, 0, 0)):
        assert compat.positive(pairs, most).count() == n_pos and compat.negative(pairs, "literal", most).count() == n_neg
    with pytest.raises(ValueError):
        compat.conflicts(pairs, "loose")


def test_lenient_conflicts_leave_out_lefts_that_also_agree(spark):
    pairs = spark.createDataFrame([("a", "x", "1"), ("a", "x", "2"), ("b", "x", "1"), ("a", "y", "1"), ("b", "y", "2")], "cand_id string, l string, r string")
    assert {r["l"] for r in compat.conflicts(pairs).collect()} == {"x", "y"}
    assert {r["l"] for r in compat.conflicts(pairs, "lenient").collect()} == {"y"}


@pytest.mark.parametrize("seed", range(12))
def test_summed_conflicts_still_part_every_strong_one(seed):
    edges = _edges(random.Random(seed), list("abcdefg"))
    part = graph.merge_greedily(edges, SynthParams(theta_edge=0.1, neg_update="sum"))
    assert all(part[a] != part[b] for a, b, _, neg in edges if neg < -0.2)


def _greedy(edges, theta, tau):
    """The plain procedure: all pairs of parts looked at for each merge."""
    parts = {v: {v} for e in edges for v in e[:2]}
    pos = {frozenset(e[:2]): e[2] for e in edges if e[2] >= theta and e[2] > 0}
    neg = {frozenset(e[:2]): e[3] for e in edges}
    while True:
        best = None
        for a, b in itertools.combinations(sorted(parts), 2):
            cross = [frozenset((x, y)) for x in parts[a] for y in parts[b]]
            w = round(sum(pos.get(c, 0) for c in cross), 9)
            if w > 0 and min(neg.get(c, 0) for c in cross) >= tau and (best is None or w > best[0]):
                best = (w, a, b)
        if best is None:
            return {v: k for k, own in parts.items() for v in own}
        parts[best[1]] |= parts.pop(best[2])


@pytest.mark.parametrize("tau", [-0.02, -0.2, -0.4, -0.6])
@pytest.mark.parametrize("seed", range(6))
def test_greedy_equals_the_plain_procedure(seed, tau):
    edges = _edges(random.Random(seed), list("abcdefgh"))
    assert graph.merge_greedily(edges, SynthParams(theta_edge=0.2, tau=tau)) == _greedy(edges, 0.2, tau)


def test_tau_sweep_equals_the_plain_procedure(spark):
    edges = [tuple(r) for r in compat.signed_graph(workloads.code_pairs(spark, SF)).select("src", "dst", "w_pos", "w_neg").collect()]
    for r in workloads.tau_sweep(spark, SF).collect():
        assert r["n_clusters"] == len(set(_greedy(edges, 0.5, r["tau"]).values()))


def test_extraction_equals_brute_force(spark):
    rng = random.Random(6)
    tables = {f"t{t}": [(f"k{k}", f"v{k % 4}", rng.choice("abc")) for k in range(20)] for t in range(3)}
    rows = [(t, "d", k, n, f"h{n}", v) for t, own in tables.items() for k, row in enumerate(own) for n, v in enumerate(row)]
    cells = spark.createDataFrame(rows, "table_id string, domain string, row_id long, col_id int, header string, value string")
    want = set()
    for t, own in tables.items():
        for a, b in itertools.permutations(range(3), 2):
            pairs = {(row[a], row[b]) for row in own}
            if len({l for l, _ in pairs}) >= 0.95 * len(pairs):
                want |= {(f"{t}|h{a}|h{b}", l, r) for l, r in pairs}
    found, stats = candidates.extract(cells)
    assert {(r["cand_id"], r["l"], r["r"]) for r in found.collect()} == want
    s = stats.first()
    assert (s["columns"], s["coherent"], s["candidates"], s["kept"]) == (9, 9, 18, len({c for c, _, _ in want}))
    strict, stats = candidates.extract(cells, SynthParams(coherence_min=0.99))
    scores = candidates.column_scores(cells.select(F.concat_ws("|", "table_id", "header").alias("col_uid"), "value").distinct())
    low = {r["col_uid"] for r in scores.where("coherence < 0.99").collect()}
    assert stats.first()["coherent"] == 9 - len(low)
    assert {(r["cand_id"], r["l"], r["r"]) for r in strict.collect()} == {w for w in want if not {f"{w[0].split('|')[0]}|{h}" for h in w[0].split("|")[1:]} & low}


def test_coherence_columns_join_once_and_agree_with_pair_scores(spark):
    cols = spark.createDataFrame([(f"c{c}", f"v{v}") for c in range(6) for v in range(8) if (c * v) % 3 != 1], "col_uid string, value string")
    scores = {(r["u"], r["v"]): r["score"] for r in candidates.pair_scores(cols).collect()}
    held: dict[str, list[str]] = {}
    for r in cols.collect():
        held.setdefault(r["col_uid"], []).append(r["value"])
    for r in candidates.column_scores(cols).collect():
        own = [scores[p] for p in itertools.combinations(sorted(held[r["col_uid"]]), 2)]
        assert r["n_pairs"] == len(own) and abs(r["coherence"] - sum(own) / len(own)) < 1e-9


def test_mixed_column_is_less_coherent(spark):
    rows = {r["col_uid"]: r["coherence"] for r in experiments.mixed_column(spark, SF).collect()}
    assert rows.pop("mixed") < min(rows.values())


def test_exact_components_equal_enumeration(spark):
    rng = random.Random(7)
    rows, want = [], {}
    for c in range(6):
        names = [f"c{c}{v}" for v in "abcde"]
        own = [(a, b, round(rng.uniform(0.1, 1), 2), -0.5 if rng.random() < 0.1 * c else 0.0) for a, b in itertools.combinations(names, 2)]
        rows += own
        want[names[0]] = exact.enumerate_best(own)[0]
    edges = spark.createDataFrame(rows, EDGE)
    got = exact.solve_components(edges, graph.components(edges)).collect()
    assert {r["comp"]: round(r["score"], 6) for r in got} == {k: round(v, 6) for k, v in want.items()} and len({r["method"] for r in got}) > 1


def test_resolution_modes(spark):
    pairs = workloads.code_pairs(spark, SF)
    one = pairs.select("cand_id").distinct().withColumn("cluster_id", F.lit("all"))
    for mode in ("pair", "table", "exact"):
        rows = conflicts.resolve(one, pairs, mode).collect()
        assert len({r["l"] for r in rows}) == len(rows) == 25
    assert conflicts.resolve(one, pairs, "none").count() == 37
    with pytest.raises(ValueError):
        conflicts.resolve(one, pairs, "best")


def test_bitmap_lookup_equals_lookup(spark):
    rng = random.Random(3)
    rows = [(f"m{m}", f"l{rng.randint(0, 60)}", f"r{rng.randint(0, 60)}") for m in range(8) for _ in range(40)]
    indexed = apps.index(spark.createDataFrame(rows, "cluster_id string, l string, r string"))
    asked = spark.createDataFrame([(f"l{k}",) for k in range(30)] + [("zz",)], "v string")
    for least in (0.2, 0.4, 0.6):
        want = {tuple(r) for r in apps.lookup(asked, indexed, least).collect()}
        assert {tuple(r) for r in apps.lookup_filtered(asked, indexed, apps.index_bits(indexed), least).collect()} == want
    assert {tuple(r) for r in apps.lookup_filtered(asked, indexed, apps.index_bits(indexed), 0.2, most=5).collect()} == {tuple(r) for r in apps.lookup(asked, indexed, 0.2).collect()}


def test_absolute_limit_takes_short_codes_for_the_same(spark):
    from mapforge.functions import text

    df = spark.createDataFrame([("usa", "rsa")], "a string, b string")
    got = df.select(text.matches(F.col("a"), F.col("b"), abs_limit=1).alias("fixed"), text.matches(F.col("a"), F.col("b")).alias("share")).first()
    assert (got["fixed"], got["share"]) == (True, False)


def test_methods_rank_as_reported(spark):
    rows = {r["method"]: r for r in experiments.case_averages(spark, SF).collect()}
    f = {m: r["avg_f"] for m, r in rows.items()}
    assert f["synthesis"] == max(f.values())
    for worse in ("synthesis_no_negative", "signed_components", "positive_components", "pivot_clusters", "header_union_domain", "header_union_corpus", "form_matcher", "single_table", "knowledge_base"):
        assert f[worse] < f["synthesis"], worse
    assert rows["single_table"]["avg_recall"] < rows["synthesis"]["avg_recall"] and rows["single_table"]["avg_precision"] >= 0.95
    assert f["knowledge_base_second"] <= f["knowledge_base"] < f["single_table"]


def test_time_cut_tables_are_partial(spark):
    full = {"s": 10, "q": 200, "y": 150}
    sizes = experiments.timed(spark, SF).groupBy("cand_id").count().collect()
    assert any(r["count"] < full.get(r["cand_id"][0], 0) for r in sizes) and len(sizes) > 50


def test_sliding_tables_cover_every_key(spark):
    part = corpus.read(spark, SF, "part")
    assert workloads.chain(spark, SF).select("l").distinct().count() == part.count()


def test_giant_components_are_merged_in_rounds(spark):
    rng = random.Random(11)
    names = [f"v{k:02}" for k in range(18)]
    weights = rng.sample(range(1, 2000), 153)
    edges = [(a, b, weights.pop() / 2000, -0.5 if rng.random() < 0.15 else 0.0) for a, b in itertools.combinations(names, 2) if rng.random() < 0.35]
    df, nodes = spark.createDataFrame(edges, EDGE), spark.createDataFrame([(n,) for n in names], "cand_id string")
    part = {r["cand_id"]: r["cluster_id"] for r in graph.synthesize(nodes, df, SynthParams(theta_edge=0.1, task_edges=0)).collect()}
    assert set(part) == set(names) and all(part[a] != part[b] for a, b, _, neg in edges if neg < -0.2)
    assert all(min(v for v in names if part[v] == c) == c for c in part.values())
    # no two parts are left that may join
    clusters = set(part.values())
    for x, y in itertools.combinations(clusters, 2):
        cross = [e for e in edges if {part[e[0]], part[e[1]]} == {x, y}]
        assert not any(e[2] >= 0.1 for e in cross) or any(e[3] < -0.2 for e in cross)


def test_rounds_equal_the_one_by_one_order_on_a_chain_of_codes(spark):
    for d_pairs in (workloads.code_pairs(spark, SF), workloads.chain(spark, SF)):
        edges = compat.signed_graph(d_pairs)
        one = {tuple(r) for r in graph.synthesize(d_pairs, edges, SynthParams(theta_edge=0.5)).collect()}
        assert {tuple(r) for r in graph.synthesize(d_pairs, edges, SynthParams(theta_edge=0.5, task_edges=0)).collect()} == one
