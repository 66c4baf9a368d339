"""Named queries over the given tables and their DuckDB equivalents."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.functions import near, text
from mapforge.operators import apps, baselines, candidates, compat, conflicts, exact, graph, measures, relaxed
from mapforge.params import SynthParams
from mapforge.plans import relational
from mapforge.sources import corpus

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = dict(relational.Q)
SQL: dict[str, str] = dict(relational.SQL)


def query(sql: str | None = None):
    def keep(f):
        Q[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


def _ring(n: int, table: str = "part", key: str = "p_partkey", left: str = "p_partkey", right: str = "p_brand", name: str = "p") -> str:
    return f"""SELECT DISTINCT '{name}' || lpad(CAST(f AS VARCHAR), 2, '0') AS cand_id, 'site' || CAST(f % 12 AS VARCHAR) AS domain, CAST({left} AS VARCHAR) AS l, CAST({right} AS VARCHAR) AS r
      FROM {table}, (SELECT count(*) AS n FROM {table}) s, (SELECT unnest(range({n})) AS f) g WHERE ((({key} - (f * n) // 50) % n) + n) % n < n // 5"""


_CODES = """SELECT c AS cand_id, n_name AS l, CASE WHEN c = 'B' AND n_nationkey % 2 = 1 THEN 'D' || n_nationkey ELSE 'C' || n_nationkey END AS r
      FROM nation, (SELECT unnest(['A1','A2','B','AB']) AS c) g WHERE c <> 'AB' OR n_nationkey % 2 = 0"""
_POS = """shared AS (SELECT a.cand_id AS src, b.cand_id AS dst, count(*) AS common FROM pairs a JOIN pairs b ON a.l = b.l AND a.r = b.r AND a.cand_id < b.cand_id GROUP BY 1, 2),
    sizes AS (SELECT cand_id, count(*) AS n FROM pairs GROUP BY 1),
    pos AS (SELECT src, dst, common, x.n AS n1, y.n AS n2, common / least(x.n, y.n) AS w FROM shared JOIN sizes x ON x.cand_id = src JOIN sizes y ON y.cand_id = dst)"""
_NEG = """clash AS (SELECT DISTINCT a.cand_id AS src, b.cand_id AS dst, a.l FROM pairs a JOIN pairs b ON a.l = b.l AND a.r <> b.r AND a.cand_id < b.cand_id),
    neg AS (SELECT src, dst, -count(*) / least(any_value(x.n), any_value(y.n)) AS w FROM clash JOIN sizes x ON x.cand_id = src JOIN sizes y ON y.cand_id = dst GROUP BY src, dst)"""


def _closure(edges: str, nodes: str = "SELECT DISTINCT cand_id AS a FROM pairs") -> str:
    """Least reachable node of every node, by a recursive query over ``edges`` (src, dst)."""
    return f"""e AS (SELECT src AS a, dst AS b FROM ({edges}) UNION SELECT dst, src FROM ({edges})),
    reach(a, b) AS (SELECT a, a FROM ({nodes}) UNION SELECT r.a, e.b FROM reach r JOIN e ON r.b = e.a),
    part AS (SELECT a AS cand_id, min(b) AS cluster_id FROM reach GROUP BY 1)"""


def chain(spark: SparkSession, d: str, n: int = 50) -> DataFrame:
    return corpus.sliding(corpus.read(spark, d, "part"), "p_partkey", "p_partkey", "p_brand", n, "p")


def code_pairs(spark: SparkSession, d: str) -> DataFrame:
    return corpus.codes(corpus.read(spark, d, "nation"))


def _flat(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if c in cols else c for c in df.columns])


_NAV = "cols AS (SELECT DISTINCT CAST(page_id AS VARCHAR) AS col_uid, unnest(regexp_extract_all(html, '<li>(?:<a[^>]*>)?([^<]+)', 1)) AS value FROM pages)"
_PAIRSCORE = _NAV + """, own AS (SELECT value, count(*) AS n FROM cols GROUP BY 1), t AS (SELECT count(DISTINCT col_uid) AS n FROM cols),
    met AS (SELECT a.value AS u, b.value AS v, count(*) AS nuv FROM cols a JOIN cols b ON a.col_uid = b.col_uid AND a.value < b.value GROUP BY 1, 2),
    scored AS (SELECT u, v, x.n AS nu, y.n AS nv, nuv, CASE WHEN nuv = t.n THEN 1.0 ELSE log10(nuv * t.n / (x.n * y.n)) / -log10(nuv / t.n) END AS score FROM met JOIN own x ON x.value = u JOIN own y ON y.value = v, t)"""


@query(f"WITH {_NAV} SELECT value, count(*) AS n FROM cols GROUP BY 1")
def col_value_counts(spark, d):
    return candidates.value_counts(corpus.nav_cells(corpus.read(spark, d, "pages")))


@query(f"WITH {_PAIRSCORE} SELECT u, v, nu, nv, nuv, round(score, 6) AS score FROM scored")
def col_pair_npmi(spark, d):
    return _flat(candidates.pair_scores(corpus.nav_cells(corpus.read(spark, d, "pages"))), "score")


@query(f"WITH {_PAIRSCORE} SELECT u, v, nu, nv, nuv, round(log10(nuv * t.n / (nu * nv)), 6) AS score FROM scored, t")
def col_pair_pmi(spark, d):
    return _flat(candidates.pair_scores(corpus.nav_cells(corpus.read(spark, d, "pages")), "pmi"), "score")


@query(f"WITH {_PAIRSCORE} SELECT a.col_uid, count(*) AS n_pairs, round(avg(score), 6) AS coherence FROM cols a JOIN cols b ON a.col_uid = b.col_uid AND a.value < b.value JOIN scored ON u = a.value AND v = b.value GROUP BY 1")
def col_coherence(spark, d):
    return _flat(candidates.column_scores(corpus.nav_cells(corpus.read(spark, d, "pages"))), "coherence")


@query(f"WITH {_PAIRSCORE}, c AS (SELECT a.col_uid, avg(score) AS s FROM cols a JOIN cols b ON a.col_uid = b.col_uid AND a.value < b.value JOIN scored ON u = a.value AND v = b.value GROUP BY 1) SELECT col_uid, value FROM cols WHERE col_uid NOT IN (SELECT col_uid FROM c WHERE s < 0.4)")
def coherent_columns(spark, d):
    return candidates.filter_columns(corpus.nav_cells(corpus.read(spark, d, "pages")), 0.4)


_WIDE = "w AS (SELECT c_custkey, c_name, c_mktsegment, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
_HEADERS = ["c_name", "c_mktsegment", "n_name", "r_name"]
_OP = "op AS (" + " UNION ALL ".join(f"SELECT '{a}' AS l_header, '{b}' AS r_header, {a} AS l, {b} AS r FROM w" for a in _HEADERS for b in _HEADERS if a != b) + ")"


def customer_pairs(spark: SparkSession, d: str) -> DataFrame:
    t = {n: corpus.read(spark, d, n) for n in ("customer", "nation", "region")}
    wide = t["customer"].join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    return candidates.column_pairs(corpus.melt(wide, F.lit("customer"), F.lit("d"), F.col("c_custkey"), _HEADERS))


@query(f"WITH {_WIDE}, {_OP} SELECT l_header, r_header, count(*) AS n_rows FROM op GROUP BY 1, 2")
def ordered_pairs(spark, d):
    return customer_pairs(spark, d).groupBy("l_header", "r_header").agg(F.count("*").alias("n_rows"))


_RATIO = f"{_WIDE}, {_OP}, ra AS (SELECT l_header, r_header, sum(n) AS n_pairs, count(*) / sum(n) AS ratio FROM (SELECT l_header, r_header, l, count(DISTINCT r) AS n FROM op GROUP BY 1, 2, 3) GROUP BY 1, 2)"


@query(f"WITH {_RATIO} SELECT l_header, r_header, CAST(n_pairs AS BIGINT) AS n_pairs, round(ratio, 6) AS ratio FROM ra")
def fd_theta_pairs(spark, d):
    return _flat(candidates.fd_ratio(customer_pairs(spark, d)).drop("table_id"), "ratio")


@query(f"WITH {_WIDE}, {_OP}, e AS (SELECT l_header, r_header, l, r, count(*) AS n FROM op GROUP BY 1, 2, 3, 4), g AS (SELECT l_header, r_header, l, max(n) AS b, sum(n) AS n FROM e GROUP BY 1, 2, 3) SELECT l_header, r_header, CAST(sum(n) AS BIGINT) AS n_pairs, round(sum(b) / sum(n), 6) AS ratio FROM g GROUP BY 1, 2")
def fd_theta_rows(spark, d):
    return _flat(candidates.fd_ratio(customer_pairs(spark, d), "rows").drop("table_id"), "ratio")


@query(f"WITH {_RATIO} SELECT l_header, r_header, CAST(n_pairs AS BIGINT) AS n_pairs FROM ra WHERE ratio = 1")
def fd_exact(spark, d):
    return candidates.fd_exact(customer_pairs(spark, d)).select("l_header", "r_header", "n_pairs")


@query(f"WITH {_RATIO}, h AS (SELECT * FROM ra WHERE ratio >= 0.95) SELECT a.l_header, a.r_header, CASE WHEN b.l_header IS NULL THEN 'N:1' ELSE '1:1' END AS cardinality FROM h a LEFT JOIN h b ON a.l_header = b.r_header AND a.r_header = b.l_header")
def cardinality_class(spark, d):
    return candidates.cardinality(candidates.fd_ratio(customer_pairs(spark, d))).drop("table_id")


@query(f"WITH {_RATIO} SELECT count(*) AS candidates, count(*) FILTER (ratio >= 0.95) AS kept, round(1 - count(*) FILTER (ratio >= 0.95) / count(*), 6) AS pruned FROM ra")
def candidate_stats(spark, d):
    return _flat(candidates.extract_stats(customer_pairs(spark, d)), "pruned")


@query(f"WITH {_RATIO} " + " UNION ALL ".join(f"SELECT {t / 100} AS theta, count(*) AS kept FROM ra WHERE ratio >= {t / 100}" for t in range(93, 98)))
def theta_sweep(spark, d):
    ratios = candidates.fd_ratio(customer_pairs(spark, d))
    grid = F.explode(F.array(*[F.lit(t / 100) for t in range(93, 98)]))
    return ratios.withColumn("theta", grid).where("ratio >= theta").groupBy("theta").agg(F.count("*").alias("kept"))


@query("SELECT DISTINCT p_name AS v, regexp_replace(lower(p_name), '[^a-z0-9]+', '', 'g') AS k FROM part")
def norm_keys(spark, d):
    return corpus.read(spark, d, "part").select(F.col("p_name").alias("v"), text.key(F.col("p_name")).alias("k")).distinct()


_NAMES = "x AS (SELECT DISTINCT n_name AS a FROM nation), y AS (SELECT a AS b FROM x), lim AS (SELECT a, b, least(length(a) // 5, length(b) // 5, 10) AS m FROM x, y WHERE a < b)"


def name_pairs(spark: SparkSession, d: str) -> DataFrame:
    names = corpus.read(spark, d, "nation").select(F.col("n_name").alias("a")).distinct()
    return names.crossJoin(names.withColumnRenamed("a", "b")).where("a < b")  # 25 names


@query(f"WITH {_NAMES} SELECT a, b, CAST(m AS BIGINT) AS m FROM lim")
def edit_limit(spark, d):
    return name_pairs(spark, d).select("a", "b", text.limit(F.col("a"), F.col("b")).cast("long").alias("m"))


@query(f"WITH {_NAMES} SELECT a, b FROM lim WHERE levenshtein(a, b) <= m")
def edit_match_band(spark, d):
    return name_pairs(spark, d).where(text.matches(F.col("a"), F.col("b"), digit_guard=False))


@query(f"WITH {_NAMES} SELECT a, b FROM lim WHERE levenshtein(a, b) <= m")
def edit_match_full(spark, d):
    return name_pairs(spark, d).where(text.matches_full(F.col("a"), F.col("b")))


@query(f"WITH {_NAMES} SELECT a, b FROM lim WHERE levenshtein(a, b) <= m AND regexp_replace(a, '[^0-9]+', ' ', 'g') = regexp_replace(b, '[^0-9]+', ' ', 'g')")
def edit_match_guarded(spark, d):
    return name_pairs(spark, d).where(text.matches(F.col("a"), F.col("b")))


@query(f"WITH pairs AS ({_ring(50)}), {_POS} SELECT src, dst, round(common / (n1 + n2 - common), 6) AS jaccard FROM pos")
def jaccard_edges(spark, d):
    return _flat(compat.jaccard(chain(spark, d)), "jaccard")


@query(f"WITH pairs AS ({_ring(50)}), {_POS} SELECT src, dst, round(common / n1, 6) AS containment FROM pos UNION ALL SELECT dst, src, round(common / n2, 6) FROM pos")
def containment_edges(spark, d):
    return _flat(compat.containment(chain(spark, d)), "containment")


@query(f"WITH pairs AS ({_ring(50)}), {_POS} SELECT src, dst, round(w, 6) AS w_pos FROM pos")
def pos_edges(spark, d):
    return _flat(compat.positive(chain(spark, d)), "w_pos")


@query(f"WITH pairs AS ({_ring(50)}), {_POS} SELECT src, dst, round(w, 6) AS w_pos FROM pos")
def pos_edges_all_pairs(spark, d):
    return _flat(compat.positive_all_pairs(chain(spark, d)), "w_pos")


@query(f"WITH pairs AS ({_CODES}), {_POS}, {_NEG} SELECT src, dst, l FROM clash")
def conflict_sets(spark, d):
    return compat.conflicts(code_pairs(spark, d))


@query(f"WITH pairs AS ({_CODES}), {_POS}, {_NEG} SELECT src, dst, round(w, 6) AS w_neg FROM neg")
def neg_edges(spark, d):
    return _flat(compat.negative(code_pairs(spark, d)), "w_neg")


@query(f"WITH pairs AS ({_CODES}), {_POS}, {_NEG} SELECT coalesce(pos.src, neg.src) AS src, coalesce(pos.dst, neg.dst) AS dst, round(coalesce(pos.w, 0), 6) AS w_pos, round(coalesce(neg.w, 0), 6) AS w_neg FROM pos FULL JOIN neg ON pos.src = neg.src AND pos.dst = neg.dst")
def signed_graph(spark, d):
    return _flat(compat.signed_graph(code_pairs(spark, d)), "w_pos", "w_neg")


_FUZZY = """first AS (SELECT p_name AS l, min(p_brand) AS r FROM part GROUP BY 1),
    raw AS (SELECT 'a' AS cand_id, l, r FROM first UNION ALL SELECT 'b', l || ' (x)', r FROM first UNION ALL SELECT 'c', 'z' || substr(l, 2), CASE WHEN length(l) % 2 = 0 THEN 'other' ELSE r END FROM first),
    pairs AS (SELECT DISTINCT cand_id, regexp_replace(lower(l), '[^a-z0-9]+', '', 'g') AS l, regexp_replace(lower(r), '[^a-z0-9]+', '', 'g') AS r FROM raw),
    sizes AS (SELECT cand_id, count(*) AS n FROM pairs GROUP BY 1),
    met AS (SELECT a.cand_id AS src, b.cand_id AS dst, a.l AS l1, b.l AS l2, a.r AS r1, b.r AS r2 FROM pairs a JOIN pairs b ON a.cand_id < b.cand_id AND (a.l = b.l OR (levenshtein(a.l, b.l) <= least(length(a.l) // 5, length(b.l) // 5, 10)
      AND trim(regexp_replace(a.l, '[^0-9]+', ' ', 'g')) = trim(regexp_replace(b.l, '[^0-9]+', ' ', 'g'))))),
    judged AS (SELECT *, r1 = r2 OR (levenshtein(r1, r2) <= least(length(r1) // 5, length(r2) // 5, 10) AND trim(regexp_replace(r1, '[^0-9]+', ' ', 'g')) = trim(regexp_replace(r2, '[^0-9]+', ' ', 'g'))) AS same FROM met),
    hits AS (SELECT src, dst, l1, r1 FROM judged WHERE l1 = l2 AND r1 = r2),
    more AS (SELECT src, dst, least(count(DISTINCT (l1, r1)), count(DISTINCT (l2, r2))) AS n FROM judged j WHERE same
      AND NOT EXISTS (SELECT 1 FROM hits h WHERE h.src = j.src AND h.dst = j.dst AND h.l1 = j.l1 AND h.r1 = j.r1) AND NOT EXISTS (SELECT 1 FROM hits h WHERE h.src = j.src AND h.dst = j.dst AND h.l1 = j.l2 AND h.r1 = j.r2) GROUP BY 1, 2),
    both_ AS (SELECT src, dst, sum(n) AS n FROM (SELECT src, dst, n FROM more UNION ALL SELECT src, dst, count(*) FROM hits GROUP BY 1, 2) GROUP BY 1, 2)"""


def spelled(spark: SparkSession, d: str) -> DataFrame:
    """Part names as they are, with a suffix, and with another first letter and partly other rights."""
    first = corpus.read(spark, d, "part").groupBy(F.col("p_name").alias("l")).agg(F.min("p_brand").alias("r"))
    rows = [("a", F.col("l"), F.col("r")), ("b", F.concat("l", F.lit(" (x)")), F.col("r")), ("c", F.concat(F.lit("z"), F.expr("substring(l, 2)")), F.when(F.length("l") % 2 == 0, "other").otherwise(F.col("r")))]
    a, b, c = (first.select(F.lit(name).alias("cand_id"), l.alias("l"), r.alias("r")) for name, l, r in rows)
    return a.union(b).union(c)


@query(f"WITH {_FUZZY} SELECT src, dst, round(b.n / least(x.n, y.n), 6) AS w_pos FROM both_ b JOIN sizes x ON x.cand_id = src JOIN sizes y ON y.cand_id = dst")
def pos_edges_fuzzy(spark, d):
    return _flat(compat.positive_fuzzy(spelled(spark, d)), "w_pos")


@query(f"WITH {_FUZZY}, c AS (SELECT src, dst, least(count(DISTINCT l1), count(DISTINCT l2)) AS n FROM judged WHERE NOT same GROUP BY 1, 2) SELECT src, dst, round(-c.n / least(x.n, y.n), 6) AS w_neg FROM c JOIN sizes x ON x.cand_id = src JOIN sizes y ON y.cand_id = dst")
def neg_edges_fuzzy(spark, d):
    return _flat(compat.negative_fuzzy(spelled(spark, d)), "w_neg")


@query("WITH v AS (SELECT DISTINCT lower(p_name) AS v FROM part) SELECT x.v AS a, y.v AS b FROM v x JOIN v y ON x.v <> y.v AND levenshtein(x.v, y.v) <= least(length(x.v) // 5, length(y.v) // 5, 10)")
def near_names(spark, d):
    return near.near_values(corpus.read(spark, d, "part").select(F.lower("p_name").alias("v")), digit_guard=False)


def aliases(spark: SparkSession, d: str) -> DataFrame:
    """Synonym feed: an alias of each nation."""
    return corpus.read(spark, d, "nation").select(F.col("n_name").alias("a"), F.concat(F.lit("zz alias "), F.col("n_nationkey")).alias("b"))


def aliased_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Two tables of nations and regions, the second naming odd nations by their alias."""
    n = corpus.read(spark, d, "nation").join(corpus.read(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    other = F.when(F.pmod("n_nationkey", F.lit(2)) == 1, F.concat(F.lit("zz alias "), F.col("n_nationkey"))).otherwise(F.col("n_name"))
    return n.select(F.lit("t1").alias("cand_id"), F.lit("d").alias("domain"), F.col("n_name").alias("l"), F.col("r_name").alias("r")).union(n.select(F.lit("t2"), F.lit("d"), other, "r_name"))


@query("SELECT n_name AS v, n_name AS canonical FROM nation UNION ALL SELECT 'zz alias ' || n_nationkey, n_name FROM nation")
def synonym_match(spark, d):
    s = aliases(spark, d)
    both = s.select(F.col("a").alias("v")).union(s.select("b"))
    return text.canonicalise(both.withColumn("canonical", F.col("v")), "canonical", s)


_ALIASED = "SELECT 't1' AS cand_id, n_name AS l, r_name AS r FROM nation JOIN region ON n_regionkey = r_regionkey UNION ALL SELECT 't2', CASE WHEN n_nationkey % 2 = 1 THEN 'zz alias ' || n_nationkey ELSE n_name END, r_name FROM nation JOIN region ON n_regionkey = r_regionkey"


@query(f"WITH named AS (SELECT n_name AS v, n_name AS canonical FROM nation UNION ALL SELECT 'zz alias ' || n_nationkey, n_name FROM nation), pairs AS (SELECT DISTINCT cand_id, coalesce(canonical, l) AS l, r FROM ({_ALIASED}) LEFT JOIN named ON v = l), {_POS} SELECT src, dst, round(w, 6) AS w_pos, 0.0 AS w_neg FROM pos")
def synonym_edges(spark, d):
    return _flat(compat.signed_graph(compat.with_synonyms(aliased_pairs(spark, d), aliases(spark, d))), "w_pos", "w_neg")


@query("SELECT n_name AS l, r_name AS r, 2 AS support FROM nation JOIN region ON n_regionkey = r_regionkey")
def resolved_synonyms(spark, d):
    pairs = compat.with_synonyms(aliased_pairs(spark, d), aliases(spark, d))
    one = pairs.select("cand_id").distinct().withColumn("cluster_id", F.lit("all"))
    return conflicts.resolve(one, pairs).select("l", "r", "support")


def per_nation(spark: SparkSession, d: str, edges: list) -> DataFrame:
    """A small graph for each nation that has suppliers: its positive weights count once for each supplier, its vertices carry the nation's key."""
    n = corpus.read(spark, d, "supplier").where("s_nationkey is not null").groupBy("s_nationkey").agg(F.count("*").alias("n"))
    named = lambda v: F.concat(F.col("s_nationkey").cast("string"), F.lit(f"|{v}"))
    laid = F.inline(F.array(*[F.struct(named(a).alias("src"), named(b).alias("dst"), (F.lit(w) * F.col("n")).alias("w_pos"), F.lit(neg).alias("w_neg")) for a, b, w, neg in edges]))
    return n.select(laid)


_PER_NATION = "(SELECT CAST(s_nationkey AS VARCHAR) AS k, count(*) AS n FROM supplier WHERE s_nationkey IS NOT NULL GROUP BY s_nationkey)"


@query(f"SELECT k || '|' || v AS cand_id, k || '|' || c AS cluster_id, round(0.6 * n, 6) AS bound, round(0.6 * n, 6) AS loss FROM {_PER_NATION}, (VALUES ('1', '1'), ('2', '1'), ('3', '3'), ('4', '3'), ('5', '3')) t(v, c)")
def relaxed_fivegraph(spark, d):
    """Distances by linear programme, rounded by growing balls, in a graph for each nation: with one negative edge the bound is met."""
    e = per_nation(spark, d, FIVE)
    return _flat(relaxed.solve_components(e, graph.components(e)).drop("comp"), "bound", "loss")


def _solved(edges: DataFrame) -> DataFrame:
    """Each component solved exactly, in a task of its own."""
    return _flat(exact.solve_components(edges, graph.components(edges)).select("comp", "method", "negatives", "score"), "score")


def _solved_sql(method: str, negatives: int, score: float) -> str:
    return f"SELECT k || '|1' AS comp, '{method}' AS method, CAST({negatives} AS BIGINT) AS negatives, round({score} * n, 6) AS score FROM {_PER_NATION}"


@query(_solved_sql("one cut", 1, 2.77))
def cut_one_neg(spark, d):
    return _solved(per_nation(spark, d, FIVE))


@query(_solved_sql("two cuts", 2, 2.1))
def cut_two_neg(spark, d):
    return _solved(per_nation(spark, d, [*[e for e in FIVE if e[:2] not in (("1", "2"), ("2", "5"))], ("2", "5", 0.30, -0.4)]))


@query(_solved_sql("enumeration", 3, 2.1))
def exact_small(spark, d):
    """Three conflicts: all partitions are tried."""
    return _solved(per_nation(spark, d, [*[e for e in FIVE if e[:2] not in (("1", "2"), ("2", "5"), ("2", "3"))], ("2", "5", 0.30, -0.4), ("2", "3", 0.30, -0.4)]))


@query(f"WITH pairs AS ({_CODES}), {_POS}, {_NEG} SELECT CAST(0.0 AS DOUBLE) AS drift, (SELECT count(DISTINCT cand_id) FROM pairs) AS n_nodes, (SELECT count(*) FROM (SELECT src, dst FROM pos UNION SELECT src, dst FROM neg)) AS n_edges")
def graph_size(spark, d):
    """Vertices and edges of the code graph; kept and cut weight together are all weight."""
    pairs = code_pairs(spark, d)
    edges = compat.signed_graph(pairs)
    parts = graph.objective(graph.synthesize(pairs, edges, SynthParams(theta_edge=0.5)), edges)
    whole = edges.agg(F.sum("w_pos").alias("w"), F.count("*").alias("n_edges"))
    n = pairs.agg(F.count_distinct("cand_id").alias("n_nodes"))
    one = parts.crossJoin(whole).crossJoin(n)  # one row each
    return one.select(F.abs(F.round(F.col("w") - F.col("score") - F.col("loss"), 6)).alias("drift"), "n_nodes", "n_edges")


@query(f"WITH RECURSIVE pairs AS ({_ring(50)}), {_POS}, {_closure('SELECT src, dst FROM pos WHERE w >= 0.85')} SELECT cand_id AS node, cluster_id AS comp FROM part")
def pos_components(spark, d):
    return graph.components(compat.positive(chain(spark, d)).where("w_pos >= 0.85"))


def _synth(pairs: DataFrame, p: SynthParams | None = None) -> DataFrame:
    return graph.synthesize(pairs, compat.signed_graph(pairs), p)


@query(f"WITH RECURSIVE pairs AS ({_ring(50)}), {_POS}, {_closure('SELECT src, dst FROM pos WHERE w >= 0.85')} SELECT cand_id, cluster_id FROM part")
def synth_chain(spark, d):
    return _synth(chain(spark, d))


@query("SELECT * FROM (VALUES ('A1', 'A1'), ('A2', 'A1'), ('AB', 'A1'), ('B', 'B')) t(cand_id, cluster_id)")
def synth_codes(spark, d):
    return _synth(code_pairs(spark, d), SynthParams(theta_edge=0.5))


@query(f"WITH RECURSIVE pairs AS ({_CODES}), {_POS}, {_closure('SELECT src, dst FROM pos WHERE w >= 0.5')} SELECT cand_id, cluster_id FROM part")
def synth_codes_no_neg(spark, d):
    return _synth(code_pairs(spark, d), SynthParams(theta_edge=0.5, use_negative=False))


#: A five-vertex graph whose best partition keeps 2.77 of positive weight.
FIVE = [("1", "2", 0.67, 0.0), ("3", "5", 0.75, 0.0), ("3", "4", 0.70, 0.0), ("4", "5", 0.65, 0.0), ("2", "3", 0.30, 0.0), ("2", "5", 0.30, 0.0), ("1", "3", 0.0, -0.5)]


def five_edges(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(FIVE, "src string, dst string, w_pos double, w_neg double")


def _five(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    e = five_edges(spark)
    return e.select(F.col("src").alias("cand_id")).union(e.select("dst")).distinct(), e


@query("SELECT * FROM (VALUES ('1', '1'), ('2', '1'), ('3', '3'), ('4', '3'), ('5', '3')) t(cand_id, cluster_id)")
def synth_fivegraph(spark, d):
    return graph.synthesize(*_five(spark), SynthParams(theta_edge=0.0))


@query("SELECT 2.77 AS score, 0.6 AS loss, 0 AS violations")
def objective_score(spark, d):
    nodes, e = _five(spark)
    return _flat(graph.objective(graph.synthesize(nodes, e, SynthParams(theta_edge=0.0)), e), "score", "loss")


_DIRTY = f"SELECT cand_id, domain, l, CASE WHEN CAST(l AS BIGINT) % 97 = 0 AND CAST(right(cand_id, 2) AS INT) % 4 = 1 THEN 'Brand#WRONG' ELSE r END AS r FROM ({_ring(50)})"


@query(f"WITH pairs AS ({_DIRTY}), u AS (SELECT l, r, count(DISTINCT cand_id) AS support FROM pairs GROUP BY 1, 2) SELECT l, r, support FROM u QUALIFY row_number() OVER (PARTITION BY l ORDER BY support DESC, r) = 1")
def resolved_pairs(spark, d):
    pairs = corpus.dirty(chain(spark, d))
    one = pairs.select("cand_id").distinct().withColumn("cluster_id", F.lit("all"))
    return conflicts.resolve(one, pairs).select("l", "r", "support")


@query("SELECT * FROM (VALUES ('A1'), ('A2'), ('AB')) t(cand_id)")
def resolved_tables(spark, d):
    pairs = code_pairs(spark, d)
    return conflicts.table_subset(pairs.select("cand_id").distinct().withColumn("cluster_id", F.lit("all")), pairs).select("cand_id")


@query("SELECT CAST(p_partkey AS VARCHAR) AS l, p_brand AS r FROM part")
def expanded_map(spark, d):
    pairs = chain(spark, d)
    core = pairs.where("cand_id in ('p00', 'p01', 'p02')").select("l", "r").distinct()
    full = corpus.read(spark, d, "part").select(F.col("p_partkey").cast("string").alias("l"), F.col("p_brand").alias("r"))
    return conflicts.expand(core, full)


@query(f"WITH RECURSIVE pairs AS ({_ring(50)}), {_POS}, {_closure('SELECT src, dst FROM pos WHERE w >= 0.85')} SELECT cluster_id, count(DISTINCT domain) AS n_domains, count(DISTINCT cand_id) AS n_tables FROM part JOIN pairs USING (cand_id) GROUP BY 1 HAVING count(DISTINCT domain) >= 8")
def popularity(spark, d):
    pairs = chain(spark, d)
    return apps.popular(apps.popularity(_synth(pairs), pairs), 8)


@query("SELECT c1, c2, n FROM (SELECT 'A1' AS c1, 'B' AS c2, count(*) AS n FROM nation)")
def cluster_overlaps(spark, d):
    pairs = code_pairs(spark, d)
    return apps.overlaps(conflicts.resolve(_synth(pairs, SynthParams(theta_edge=0.5)), pairs))


@query("SELECT n_name AS l, 'D' || n_nationkey AS r, 'added' AS change FROM nation WHERE n_nationkey % 2 = 1 UNION ALL SELECT n_name, 'C' || n_nationkey, 'removed' FROM nation WHERE n_nationkey % 2 = 1")
def run_diff(spark, d):
    pairs = code_pairs(spark, d)
    return apps.diff(pairs.where("cand_id = 'A1'"), pairs.where("cand_id = 'B'"))


@query(f"WITH pairs AS ({_CODES}), m AS (SELECT DISTINCT CASE cand_id WHEN 'B' THEN 'B' ELSE 'A1' END AS cluster_id, l FROM pairs) SELECT cluster_id, 'l' AS side, count(*) / (SELECT count(DISTINCT n_name) FROM nation) AS containment FROM m WHERE l IN (SELECT n_name FROM nation) GROUP BY 1")
def map_lookup(spark, d):
    pairs = code_pairs(spark, d)
    mapping = conflicts.resolve(_synth(pairs, SynthParams(theta_edge=0.5)), pairs)
    return apps.lookup(corpus.read(spark, d, "nation").select(F.col("n_name").alias("v")), apps.index(mapping))


@query("SELECT c_custkey, CASE WHEN c_custkey % 5 = 0 THEN 'C' || n_nationkey ELSE n_name END AS v, n_name AS suggested FROM customer JOIN nation ON c_nationkey = n_nationkey")
def auto_correct(spark, d):
    cust = corpus.read(spark, d, "customer").join(corpus.read(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    mixed = cust.select("c_custkey", F.when(F.pmod("c_custkey", F.lit(5)) == 0, F.concat(F.lit("C"), F.col("n_nationkey"))).otherwise(F.col("n_name")).alias("v"))
    return apps.auto_correct(mixed, "v", code_pairs(spark, d).where("cand_id = 'A1'"))


@query("SELECT c_name, n_name AS filled FROM customer JOIN nation ON c_nationkey = n_nationkey")
def auto_fill(spark, d):
    kb = baselines.kb_relations(corpus.triples(spark, d)).withColumnRenamed("relation_id", "cluster_id")
    some = kb.where("cluster_id = 'of_nation'").orderBy("l").limit(2).select("l", "r")
    return apps.auto_fill(corpus.read(spark, d, "customer").select("c_name"), "c_name", some, kb)


@query("SELECT s_name, 'C' || n_nationkey AS code, n_regionkey FROM supplier JOIN nation ON s_nationkey = n_nationkey")
def auto_join(spark, d):
    nation = corpus.read(spark, d, "nation")
    named = corpus.read(spark, d, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_name", "n_name")
    coded = nation.select(F.concat(F.lit("C"), F.col("n_nationkey")).alias("code"), "n_regionkey")
    return apps.auto_join(named, "n_name", coded, "code", code_pairs(spark, d).where("cand_id = 'A1'")).select("s_name", "code", "n_regionkey")


def headed(spark: SparkSession, d: str) -> DataFrame:
    h = F.element_at(F.array(F.lit("name"), F.lit("code"), F.lit("id")), F.pmod(F.substring("cand_id", -2, 2).cast("int"), F.lit(3)) + 1)
    return chain(spark, d).select("cand_id", "domain", h.alias("l_header"), F.lit("brand").alias("r_header"), F.lit("int").alias("l_type"), F.lit("string").alias("r_type")).distinct()


_HEADED = f"SELECT DISTINCT cand_id, domain, ['name','code','id'][CAST(right(cand_id, 2) AS INT) % 3 + 1] AS h FROM ({_ring(50)})"


@query(f"SELECT cand_id, domain || '|' || h || '|brand' AS cluster_id FROM ({_HEADED})")
def hdr_union_site(spark, d):
    return baselines.header_union(headed(spark, d))


@query(f"SELECT cand_id, h || '|brand' AS cluster_id FROM ({_HEADED})")
def hdr_union_corpus(spark, d):
    return baselines.header_union(headed(spark, d), "corpus")


@query()
def form_matcher(spark, d):
    h = headed(spark, d)
    return baselines.form_matcher(h, h, 0.4)


@query(f"WITH RECURSIVE pairs AS ({_CODES}), {_POS}, {_NEG}, mix AS (SELECT coalesce(pos.src, neg.src) AS src, coalesce(pos.dst, neg.dst) AS dst, 0.5 * coalesce(pos.w, 0) + 0.5 * coalesce(neg.w, 0) AS w FROM pos FULL JOIN neg ON pos.src = neg.src AND pos.dst = neg.dst), {_closure('SELECT src, dst FROM mix WHERE w >= 0.4')} SELECT cand_id, cluster_id FROM part")
def signed_cc(spark, d):
    pairs = code_pairs(spark, d)
    return baselines.signed_components(pairs, compat.signed_graph(pairs), 0.5, 0.4)


@query(f"WITH RECURSIVE pairs AS ({_ring(50)}), {_POS}, {_closure('SELECT src, dst FROM pos WHERE w >= 0.85')} SELECT cand_id, cluster_id FROM part")
def positive_cc(spark, d):
    pairs = chain(spark, d)
    return baselines.positive_components(pairs, compat.signed_graph(pairs), 0.85)


@query()
def pivot_cc(spark, d):
    pairs = chain(spark, d)
    return baselines.pivot_clusters(pairs, compat.signed_graph(pairs))


_KB1 = "SELECT n_name AS s, 'in_region' AS p, r_name AS o FROM nation JOIN region ON n_regionkey = r_regionkey UNION ALL SELECT c_name, 'of_nation', n_name FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT CAST(p_partkey AS VARCHAR), 'brand', p_brand FROM part"
_KB2 = "SELECT n_name AS s, 'in_region' AS p, r_name AS o FROM nation JOIN region ON n_regionkey = r_regionkey UNION ALL SELECT n_name, 'code', CAST(n_nationkey AS VARCHAR) FROM nation"


@query(f"WITH t AS ({_KB1}) SELECT DISTINCT p AS relation_id, s AS l, o AS r FROM t UNION SELECT DISTINCT p || '~', o, s FROM t")
def kb_relations(spark, d):
    return baselines.kb_relations(corpus.triples(spark, d))


@query(f"WITH t AS ({_KB2}) SELECT DISTINCT p AS relation_id, s AS l, o AS r FROM t UNION SELECT DISTINCT p || '~', o, s FROM t")
def kb_relations_second(spark, d):
    return baselines.kb_relations(corpus.triples(spark, d, 2))


def truth(spark: SparkSession, d: str) -> DataFrame:
    """Cases: part to brand, name to first code, name to second code."""
    codes = code_pairs(spark, d)
    part = corpus.read(spark, d, "part").select(F.lit("part_brand").alias("case_id"), F.col("p_partkey").cast("string").alias("l"), F.col("p_brand").alias("r"))
    return part.union(codes.where("cand_id = 'A1'").select(F.lit("code_a"), "l", "r")).union(codes.where("cand_id = 'B'").select(F.lit("code_b"), "l", "r"))


_TRUTH = f"truth AS (SELECT 'part_brand' AS case_id, CAST(p_partkey AS VARCHAR) AS l, p_brand AS r FROM part UNION ALL SELECT CASE cand_id WHEN 'A1' THEN 'code_a' ELSE 'code_b' END, l, r FROM ({_CODES}) WHERE cand_id IN ('A1', 'B'))"
_RAW = f"rel AS (SELECT cand_id AS relation_id, l, r FROM ({_ring(50)}) UNION ALL SELECT cand_id, l, r FROM ({_CODES}))"
_PRF = "prf AS (SELECT case_id, relation_id, h / nr AS precision, h / nc AS recall, 2 * h / (nr + nc) AS f FROM (SELECT case_id, relation_id, count(*) AS h FROM rel JOIN truth USING (l, r) GROUP BY 1, 2) JOIN (SELECT relation_id, count(*) AS nr FROM rel GROUP BY 1) USING (relation_id) JOIN (SELECT case_id, count(*) AS nc FROM truth GROUP BY 1) USING (case_id))"


def corpus_pairs(spark: SparkSession, d: str) -> DataFrame:
    return chain(spark, d).unionByName(code_pairs(spark, d))


def _mapped(spark: SparkSession, d: str, p: SynthParams) -> DataFrame:
    pairs = corpus_pairs(spark, d)
    return conflicts.resolve(_synth(pairs, p), pairs).select(F.col("cluster_id").alias("relation_id"), "l", "r")


@query(f"WITH {_TRUTH}, {_RAW}, {_PRF} SELECT case_id, relation_id, round(precision, 6) AS precision, round(recall, 6) AS recall, round(f, 6) AS f FROM prf")
def case_prf_raw_tables(spark, d):
    raw = corpus_pairs(spark, d).select(F.col("cand_id").alias("relation_id"), "l", "r")
    return _flat(measures.prf(raw, truth(spark, d)), "precision", "recall", "f")


@query(f"WITH {_TRUTH}, {_RAW}, {_PRF}, b AS (SELECT case_id, max(f) AS f FROM prf GROUP BY 1) SELECT round(avg(f), 6) AS avg_f FROM b")
def best_single_all(spark, d):
    raw = corpus_pairs(spark, d).select(F.col("cand_id").alias("relation_id"), "l", "r")
    t = truth(spark, d)
    return _flat(measures.summary(measures.best_relation(measures.prf(raw, t)), t).select("avg_f"), "avg_f")


@query(f"WITH {_TRUTH}, {_RAW}, {_PRF}, b AS (SELECT case_id, max(f) AS f FROM prf JOIN (SELECT DISTINCT cand_id AS relation_id FROM ({_ring(50)}) WHERE domain = 'site0' UNION SELECT 'A1') USING (relation_id) GROUP BY 1) SELECT round(sum(f) / 3, 6) AS avg_f FROM b")
def best_single_trusted(spark, d):
    raw = corpus_pairs(spark, d).where("domain = 'site0'").select(F.col("cand_id").alias("relation_id"), "l", "r")
    t = truth(spark, d)
    return _flat(measures.summary(measures.best_relation(measures.prf(raw, t)), t).select("avg_f"), "avg_f")


@query("SELECT * FROM (VALUES ('part_brand', 1.0, 1.0, 1.0), ('code_a', 1.0, 1.0, 1.0), ('code_b', 1.0, 1.0, 1.0)) t(case_id, precision, recall, f)")
def case_prf_synthesis(spark, d):
    scores = measures.prf(_mapped(spark, d, SynthParams(theta_edge=0.5)), truth(spark, d))
    return _flat(measures.best_relation(scores), "precision", "recall", "f").drop("relation_id")


@query("SELECT CAST(1.0 AS DOUBLE) AS avg_f, CAST(1.0 AS DOUBLE) AS avg_precision, CAST(1.0 AS DOUBLE) AS avg_recall")
def case_summary(spark, d):
    t = truth(spark, d)
    return _flat(measures.summary(measures.best_relation(measures.prf(_mapped(spark, d, SynthParams(theta_edge=0.5)), t)), t), "avg_f", "avg_precision", "avg_recall")


@query()
def case_summary_no_neg(spark, d):
    t = truth(spark, d)
    return _flat(measures.summary(measures.best_relation(measures.prf(_mapped(spark, d, SynthParams(theta_edge=0.5, use_negative=False)), t)), t), "avg_f", "avg_precision", "avg_recall")


@query(f"WITH pairs AS ({_ring(50)}), {_POS} " + " UNION ALL ".join(f"SELECT {k} AS theta_overlap, count(*) AS n_edges FROM pos WHERE common > {k}" for k in (0, 1, 2, 5, 10)))
def overlap_sweep(spark, d):
    grid = F.explode(F.array(*map(F.lit, (0, 1, 2, 5, 10))))
    return compat.shared(chain(spark, d)).withColumn("theta_overlap", grid).where("common > theta_overlap").groupBy("theta_overlap").agg(F.count("*").alias("n_edges"))


@query(f"WITH pairs AS ({_ring(50)}), {_POS} SELECT t AS theta_edge, count(*) AS n_edges FROM pos, (SELECT unnest([0.5, 0.65, 0.75, 0.85]) AS t) WHERE w >= CAST(t AS DOUBLE) GROUP BY 1")
def edge_sweep(spark, d):
    grid = F.explode(F.array(*map(F.lit, (0.5, 0.65, 0.75, 0.85))))
    return compat.positive(chain(spark, d)).withColumn("theta_edge", grid).where("w_pos >= theta_edge").groupBy("theta_edge").agg(F.count("*").alias("n_edges"))


@query()
def tau_sweep(spark, d):
    pairs = code_pairs(spark, d)
    edges = compat.signed_graph(pairs)
    out = None
    for tau in (-0.02, -0.05, -0.1, -0.2, -0.4):
        one = graph.synthesize(pairs, edges, SynthParams(theta_edge=0.5, tau=tau)).agg(F.lit(tau).alias("tau"), F.count_distinct("cluster_id").alias("n_clusters"))
        out = one if out is None else out.union(one)
    return out


@query(f"WITH all_pairs AS ({_ring(50)}) " + " UNION ALL ".join(f"SELECT {k} AS percent, count(*) AS n_edges FROM (SELECT DISTINCT a.cand_id, b.cand_id AS other FROM all_pairs a JOIN all_pairs b ON a.l = b.l AND a.r = b.r AND a.cand_id < b.cand_id WHERE CAST(right(a.cand_id, 2) AS INT) % 5 < {k // 20} AND CAST(right(b.cand_id, 2) AS INT) % 5 < {k // 20})" for k in (20, 40, 60, 80, 100)))
def scale_samples(spark, d):
    s = compat.shared(chain(spark, d))
    fold = F.greatest(*[F.pmod(F.substring(c, -2, 2).cast("int"), F.lit(5)) for c in ("src", "dst")])
    grid = F.explode(F.array(*map(F.lit, (20, 40, 60, 80, 100))))
    return s.withColumn("percent", grid).where(fold < F.col("percent") / 20).groupBy("percent").agg(F.count("*").alias("n_edges"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem WHERE l_shipdate < TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def rel_aggregate(spark, d):
    return corpus.read(spark, d, "lineitem").where(F.col("l_shipdate") < F.lit("1998-09-02").cast("timestamp_ntz")).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("SELECT c_mktsegment, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY CUBE (c_mktsegment, n_name)")
def rel_cube(spark, d):
    return corpus.read(spark, d, "customer").join(F.broadcast(corpus.read(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).cube("c_mktsegment", "n_name").agg(F.count("*").alias("n"))


@query("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def rel_topk_window(spark, d):
    from pyspark.sql import Window

    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return corpus.read(spark, d, "orders").withColumn("k", F.row_number().over(w)).where("k <= 3").select("o_custkey", "o_orderkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def rel_anti_join(spark, d):
    return corpus.read(spark, d, "customer").join(corpus.read(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """A ring of fifty partial tables in, one conflict-free mapping out."""
    pairs = corpus.dirty(chain(spark, d))
    return conflicts.resolve(_synth(pairs, SynthParams(theta_edge=0.75)), pairs)
