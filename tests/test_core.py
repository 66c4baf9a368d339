from __future__ import annotations

import itertools
import random

import pytest

from mapforge.functions import near, text
from mapforge.operators import candidates, compat, conflicts, exact, graph, relaxed
from mapforge.params import SynthParams
from mapforge.plans import workloads


def test_pmi_of_the_example(spark):
    row = spark.range(1).selectExpr("1000.0D nu", "500.0D nv", "300.0D nuv", "1e8 n")
    from pyspark.sql import functions as F

    cols = [F.col(c) for c in ("nu", "nv", "nuv", "n")]
    got = row.select(text.pmi(*cols).alias("p"), text.npmi(*cols).alias("s")).first()
    assert round(got["p"], 2) == 4.78
    assert round(got["s"], 4) == 0.8652


def test_edit_limit_of_the_example(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([("American Samoa", "American Samoa (US)")], "a string, b string").select(text.key(F.col("a")).alias("a"), text.key(F.col("b")).alias("b"))
    got = df.select(text.limit(F.col("a"), F.col("b")).alias("m"), F.levenshtein("a", "b").alias("d"), text.matches(F.col("a"), F.col("b")).alias("ok")).first()
    assert (got["m"], got["d"], got["ok"]) == (2, 2, True)


def test_weights_are_bounded(spark):
    edges = workloads.signed_graph(spark, "/root/testdata/sf0.001").collect()
    assert edges and all(0 <= e["w_pos"] <= 1 and -1 <= e["w_neg"] <= 0 and e["w_pos"] - e["w_neg"] <= 1 + 1e-9 for e in edges)


def test_index_join_equals_all_pairs(spark):
    pairs = workloads.code_pairs(spark, "/root/testdata/sf0.001")
    want = {(r["src"], r["dst"]): r["w_pos"] for r in compat.positive_all_pairs(pairs).collect()}
    assert {(r["src"], r["dst"]): r["w_pos"] for r in compat.positive(pairs).collect()} == want


@pytest.mark.parametrize("seed", range(40))
def test_greedy_is_feasible_and_no_better_than_the_optimum(seed):
    rng = random.Random(seed)
    nodes = "abcdef"
    edges = [(a, b, rng.choice([0, 0.5, 0.9]), rng.choice([0, 0, -0.5])) for a, b in itertools.combinations(nodes, 2)]
    part = graph.merge_greedily(edges, SynthParams(theta_edge=0.1))
    groups = {}
    for v, c in part.items():
        groups.setdefault(c, []).append(v)
    got = exact.score(list(groups.values()), edges, -0.2)
    assert got is not None and got <= exact.enumerate_best(edges)[0] + 1e-9


@pytest.mark.parametrize("seed", range(40))
@pytest.mark.parametrize("negatives", [1, 2])
def test_cuts_equal_enumeration(seed, negatives):
    rng = random.Random(seed)
    all_ = list(itertools.combinations("abcdef", 2))
    bad = set(rng.sample(all_, negatives))
    edges = [(a, b, round(rng.random(), 3), -0.5 if (a, b) in bad else 0.0) for a, b in all_]
    assert abs(exact.solve(edges) - exact.enumerate_best(edges)[0]) < 1e-6


def test_five_vertices():
    assert round(exact.enumerate_best(workloads.FIVE)[0], 2) == 2.77
    assert exact.enumerate_best(workloads.FIVE)[1] == [["1", "2"], ["3", "4", "5"]]


def test_majority_equals_iterative_removal(spark):
    rng = random.Random(4)
    rows = sorted({(f"t{rng.randint(0, 9)}", "d", f"l{rng.randint(0, 5)}", f"r{rng.randint(0, 3)}") for _ in range(80)})
    left = [(c, l, r) for c, _, l, r in rows]
    while True:
        clash = {x: sum(y[1] == x[1] and y[2] != x[2] for y in left) for x in left}
        worst = max(left, key=lambda x: (clash[x], x[2], x[0]), default=None)
        if worst is None or not clash[worst]:
            break
        left.remove(worst)
    pairs = spark.createDataFrame(rows, "cand_id string, domain string, l string, r string")
    from pyspark.sql import functions as F

    one = pairs.select("cand_id").distinct().withColumn("cluster_id", F.lit("x"))
    got = {(r["l"], r["r"]) for r in conflicts.resolve(one, pairs).collect()}
    assert got == {(l, r) for _, l, r in left}


def test_best_subset():
    tables = {"a": {("x", "1")}, "b": {("x", "2"), ("y", "1")}, "c": {("y", "1"), ("z", "1")}}
    chosen, n = conflicts.best_subset(tables)
    assert n == 3 and "c" in chosen  # with either of the other two


def test_theta_bounds(spark):
    pairs = spark.createDataFrame([("t", "a", "b", f"l{k}", f"r{k}") for k in range(19)] + [("t", "a", "b", "l0", "other")], "table_id string, l_header string, r_header string, l string, r string")
    assert candidates.fd_approx(pairs, 0.95).count() == 1
    assert candidates.fd_approx(pairs, 0.96).count() == 0


def test_flagship(spark):
    rows = workloads.flagship(spark, "/root/testdata/sf0.001").collect()
    assert rows and len({(r["cluster_id"], r["l"]) for r in rows}) == len(rows)


def _edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_near_values_equal_brute_force(spark):
    rng = random.Random(8)
    values = {"", "a", "é" * 5}
    for _ in range(40):
        base = "".join(rng.choices("abc", k=rng.randint(1, 34)))
        values.add(base)
        for _ in range(3):
            other = list(base)
            for _ in range(rng.randint(1, 7)):
                k = rng.randrange(len(other) + 1)
                other[k : k + rng.randint(0, 1)] = rng.choice(["", "x", "b"])
            values.add("".join(other))
    want = {(a, b) for a in values for b in values if a != b and _edits(a, b) <= min(len(a) // 5, len(b) // 5, 10)}
    rows = spark.createDataFrame([(v,) for v in [*values, None]], "v string")
    got = [(r["a"], r["b"]) for r in near.near_values(rows, digit_guard=False).collect()]
    assert len(want) > 50 and sorted(got) == sorted(want)
    assert near.near_values(rows.limit(0)).count() == 0


@pytest.mark.parametrize("seed", range(25))
def test_relaxation_bounds_the_optimum(seed):
    rng = random.Random(seed)
    edges = [(a, b, round(rng.random(), 2), rng.choice([0, 0, -0.5])) for a, b in itertools.combinations("abcdef", 2)]
    bound, loss, home = relaxed.rounded(edges)
    best = sum(e[2] for e in edges) - exact.enumerate_best(edges)[0]
    assert bound <= best + 1e-6 and loss >= best - 1e-6
    assert all(home[a] != home[b] for a, b, _, neg in edges if neg < -0.2)


def test_relaxation_is_exact_for_one_negative_edge():
    bound, loss, _ = relaxed.rounded(workloads.FIVE)
    assert abs(bound - 0.6) < 1e-6 and abs(loss - 0.6) < 1e-6


def test_components_beyond_the_relaxation_stay_alone(spark):
    e = spark.createDataFrame([(f"v{k:02}", f"v{k + 1:02}", 0.5, 0.0) for k in range(14)] + [("x", "y", 0.5, 0.0)], "src string, dst string, w_pos double, w_neg double")
    rows = relaxed.solve_components(e, graph.components(e)).collect()
    assert len(rows) == 17 and sum(r["bound"] is None and r["cand_id"] == r["cluster_id"] for r in rows) == 15


def test_spelling_is_no_conflict(spark):
    rows = [("a", "American Samoa", "Pago Pago"), ("b", "American Samoa (US)", "Pago-Pago"), ("a", "Tonga", "x"), ("b", "Tonga", "yyyyy")]
    got = {(r["src"], r["dst"]): r["w_neg"] for r in compat.negative_fuzzy(spark.createDataFrame(rows, "cand_id string, l string, r string")).collect()}
    assert got == {("a", "b"): -0.5}


@pytest.mark.parametrize("local_edges", [0, 10_000])
def test_components_equal_brute_force(spark, local_edges):
    rng = random.Random(3)
    names = [f"v{k:03}" for k in range(120)]
    pairs = [(rng.choice(names), rng.choice(names)) for _ in range(70)] + [("v050", f"w{k}") for k in range(40)] + [(None, "v001"), ("v002", "v002")]
    left = {v: v for p in pairs for v in p}
    for _ in left:
        for a, b in pairs:
            if a and b:
                left[a] = left[b] = min(left[a], left[b])
    ends = {v for a, b in pairs if a and b and a != b for v in (a, b)}
    df = spark.createDataFrame(pairs, "src string, dst string")
    got = {r["node"]: r["comp"] for r in graph.components(df, local_edges=local_edges, hot_edges=5).collect()}
    assert got == {v: left[v] for v in ends}
    assert graph.components(df.limit(0), local_edges=local_edges).count() == 0


def test_components_that_do_not_settle_raise(spark):
    chain = spark.range(400).selectExpr("format_string('%04d', id) as src", "format_string('%04d', id + 1) as dst")
    with pytest.raises(RuntimeError):
        graph.components(chain, max_rounds=1, local_edges=0)
