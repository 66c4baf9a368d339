"""The rest of the relational, streaming and function surface, each query with its DuckDB equivalent."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mapforge import streaming
from mapforge.functions import registered
from mapforge.operators import apps, baselines, candidates
from mapforge.plans.workloads import _CODES, _OP, _WIDE, _ring, chain, code_pairs, customer_pairs, headed
from mapforge.sources import corpus
from mapforge.sources.storage import shared_dir, stage

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        Q[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


@query("SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")
def rel_percentiles(spark, d):
    at = lambda p: F.round(F.percentile("l_extendedprice", p), 4)
    return corpus.read(spark, d, "lineitem").groupBy("l_returnflag").agg(at(0.5).alias("median"), at(0.9).alias("p90"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS n_parts, true AS hll_near, true AS theta_near, true AS approx_near FROM lineitem GROUP BY 1")
def rel_sketches(spark, d):
    """Distinct counts by sketches, each within 6 % of the exact one."""
    near = lambda c: (F.abs(c - F.col("n_parts")) <= 0.06 * F.col("n_parts"))
    got = corpus.read(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.count_distinct("l_partkey").alias("n_parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("h"),
        F.expr("theta_sketch_estimate(theta_sketch_agg(l_partkey))").alias("t"), F.approx_count_distinct("l_partkey", 0.02).alias("a"),
    )
    return got.select("l_returnflag", "n_parts", near(F.col("h")).alias("hll_near"), near(F.col("t")).alias("theta_near"), near(F.col("a")).alias("approx_near"))


@query("""SELECT o_orderkey, ntile(4) OVER w AS quarter_of, lead(o_orderkey) OVER w AS next_order, first_value(o_orderkey) OVER w AS first_order,
    rank() OVER w AS place, dense_rank() OVER w AS dense, last_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_order
    FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""")
def rel_window_functions(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    o = corpus.read(spark, d, "orders")
    return o.select("o_orderkey", F.ntile(4).over(w).alias("quarter_of"), F.lead("o_orderkey").over(w).alias("next_order"), F.first("o_orderkey").over(w).alias("first_order"), F.rank().over(w).alias("place"), F.dense_rank().over(w).alias("dense"), F.last("o_orderkey").over(whole).alias("last_order"))


@query("SELECT event_type, CAST(json_extract(props, '$.k') AS INTEGER) AS k, CAST(json_extract(props, '$.k') AS INTEGER) AS variant_k, count(*) AS n FROM events GROUP BY 1, 2")
def rel_from_json(spark, d):
    e = corpus.read(spark, d, "events").select("event_type", F.from_json("props", "k int")["k"].alias("k"), F.try_variant_get(F.try_parse_json("props"), "$.k", "int").alias("variant_k"))
    return e.groupBy("event_type", "k", "variant_k").agg(F.count("*").alias("n"))


@query("SELECT s AS strategy, (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) AS n FROM (SELECT unnest(['broadcast', 'merge', 'shuffle_hash']) AS s)")
def rel_join_strategies(spark, d):
    """The same join by each physical strategy."""
    o, c = corpus.read(spark, d, "orders"), corpus.read(spark, d, "customer")
    out = None
    for name in ("broadcast", "merge", "shuffle_hash"):
        one = o.join(c.hint(name), F.col("o_custkey") == F.col("c_custkey")).agg(F.count("*").alias("n")).select(F.lit(name).alias("strategy"), "n")
        out = one if out is None else out.union(one)
    return out


@query("SELECT f AS format, n_regionkey AS region, count(*) AS n, min(n_name) AS first_name FROM nation, (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS f) GROUP BY 1, 2")
def rel_sinks(spark, d):
    """Nations written in each file format, divided by region, one region overwritten alone, and read back."""
    nation = corpus.read(spark, d, "nation")
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        path = f"{shared_dir(spark)}/sink-{kind}-{uuid.uuid4().hex}"
        part = nation.withColumn("region", F.col("n_regionkey"))
        head = {"header": "true"} if kind == "csv" else {}
        part.write.partitionBy("region").format(kind).options(**head).save(path)
        part.where("region = 1").write.option("partitionOverwriteMode", "dynamic").partitionBy("region").format(kind).options(**head).mode("overwrite").save(path)
        back = spark.read.format(kind).options(**head).schema(part.schema).load(path)
        one = back.groupBy("region").agg(F.count("*").alias("n"), F.min("n_name").alias("first_name")).select(F.lit(kind).alias("format"), "region", "n", "first_name")
        out = one if out is None else out.union(one)
    return out


@query("""WITH t AS (SELECT 'embeddings' AS name, CAST(vec_id AS VARCHAR) AS l, CAST(label AS VARCHAR) AS r FROM embeddings UNION ALL SELECT 'labels', CAST(doc_id AS VARCHAR), CAST(toxic AS VARCHAR) FROM labels
    UNION ALL SELECT 'benchmark', CAST(item_id AS VARCHAR), md5(text) FROM benchmark UNION ALL SELECT 'turns', CAST(turn AS VARCHAR), role FROM conversations UNION ALL SELECT 'conversations', conv_id || '/' || turn, role FROM conversations)
    SELECT name, CAST(sum(n) AS BIGINT) AS n_pairs, round(count(*) / sum(n), 6) AS ratio FROM (SELECT name, l, count(DISTINCT r) AS n FROM t WHERE l IS NOT NULL AND r IS NOT NULL GROUP BY 1, 2) GROUP BY 1""")
def given_tables_fd(spark, d):
    """How functional the key columns of the other given tables are."""
    t = {n: corpus.read(spark, d, n) for n in ("embeddings", "labels", "benchmark", "conversations")}
    rows = [("embeddings", t["embeddings"], F.col("vec_id"), F.col("label")), ("labels", t["labels"], F.col("doc_id"), F.col("toxic")), ("benchmark", t["benchmark"], F.col("item_id"), F.md5("text")), ("turns", t["conversations"], F.col("turn"), F.col("role")), ("conversations", t["conversations"], F.concat_ws("/", "conv_id", "turn"), F.col("role"))]
    out = None
    for name, df, l, r in rows:
        one = df.select(F.lit(name).alias("table_id"), F.lit("l").alias("l_header"), F.lit("r").alias("r_header"), l.cast("string").alias("l"), r.cast("string").alias("r")).where("l is not null and r is not null")
        out = one if out is None else out.union(one)
    return candidates.fd_ratio(out).select(F.col("table_id").alias("name"), "n_pairs", F.round("ratio", 6).alias("ratio"))


# ---- streams ----

_FIRST, _SECOND = "2024-01-10 00:00:00", "2024-01-15 00:00:00"


def _arriving(spark: SparkSession, d: str) -> list[DataFrame]:
    """Events in three arrivals by time; every tenth one of the first period comes late, with the last."""
    e = corpus.read(spark, d, "events")
    at = lambda t: F.lit(t).cast("timestamp_ntz")
    first = (F.col("ts") < at(_FIRST)) & (F.pmod("event_id", F.lit(10)) != 0)
    second = (F.col("ts") >= at(_FIRST)) & (F.col("ts") < at(_SECOND))
    return [e.where(first), e.where(second), e.where(~first & ~second)]


_EARLY = f"(ts < TIMESTAMP '{_FIRST}' AND event_id % 10 <> 0)"
_LATER = f"(ts >= TIMESTAMP '{_FIRST}' AND ts < TIMESTAMP '{_SECOND}')"


@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_windows(spark, d):
    """Hourly counts of a stream, all kept to its end."""
    counts = streaming.event_windows(streaming.events_stream(spark, d))
    return streaming.run_updates(spark, counts, "windows", ["start", "event_type"], "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(f"WITH wm AS (SELECT max(ts) - INTERVAL 10 MINUTE AS newest FROM events WHERE {_EARLY}) SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events, wm WHERE {_EARLY} OR date_trunc('hour', ts) + INTERVAL 1 HOUR > newest GROUP BY 1, 2")
def stream_late(spark, d):
    """Hourly counts where events of windows behind the watermark come too late and are dropped.

    A batch drops what is behind the watermark that the batch before it went by, so the first arrival's counts in the third.
    """
    counts = streaming.event_windows(streaming.arrivals(spark, _arriving(spark, d), "late"))
    return streaming.run_updates(spark, counts, "late", ["start", "event_type"]).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS opens FROM events), s AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_sessions(spark, d):
    """Sessions of each user in a stream."""
    found = streaming.sessions(streaming.events_stream(spark, d))
    return streaming.run_updates(spark, found, "sessions", ["user_id", "start"], "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(f"SELECT user_id, event_type, count(*) AS support, count(*) FILTER (NOT {_EARLY} AND NOT {_LATER}) > 0 AS changed FROM events GROUP BY 1, 2")
def stream_upserts(spark, d):
    """Counters of (user, type) kept over three arrivals, with those that the last one changed."""
    stream = streaming.arrivals(spark, _arriving(spark, d), "upserts").select("user_id", "event_type")
    return streaming.upsert_counts(spark, stream, "upserts", ["user_id", "event_type"])


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, d):
    """First arrival of each (user, type) of a month; state goes a month after the newest event."""
    first = streaming.distinct_within(streaming.events_stream(spark, d), ["user_id", "event_type"], "60 days").select("user_id", "event_type")
    return streaming.run_to_table(spark, first, "dedup")


# ---- functions ----


@query(f"WITH {_WIDE}, {_OP} SELECT l_header, r_header, round(count(DISTINCT l) / count(DISTINCT (l, r)), 6) AS theta FROM op GROUP BY 1, 2")
def udf_theta(spark, d):
    """The functional share by a grouped pandas function."""
    return customer_pairs(spark, d).groupBy("l_header", "r_header").agg(F.round(registered.theta_of("l", "r"), 6).alias("theta"))


@query(f"WITH {_WIDE}, {_OP} SELECT l_header, r_header, count(*) AS n_rows, count(DISTINCT (l, r)) AS n_pairs FROM op GROUP BY 1, 2")
def udtf_column_pairs(spark, d):
    """Ordered column pairs by the registered table function, from SQL."""
    registered.register(spark)
    t = {n: corpus.read(spark, d, n) for n in ("customer", "nation", "region")}
    wide = t["customer"].join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    rows = wide.select(F.array(*map(F.lit, ("c_name", "c_mktsegment", "n_name", "r_name"))).alias("headers"), F.array("c_name", "c_mktsegment", "n_name", "r_name").alias("cells"))
    return spark.sql("SELECT l_header, r_header, count(*) AS n_rows, count(DISTINCT l, r) AS n_pairs FROM {rows}, LATERAL column_pairs_of(headers, cells) GROUP BY 1, 2", rows=rows)


@query("SELECT n_name, 'C' || n_nationkey AS code, CAST(least(length(n_name) // 5, 10) AS INTEGER) AS most FROM nation")
def sql_functions(spark, d):
    """Lookup in a mapping and the edit limit, from SQL."""
    registered.register(spark, code_pairs(spark, d).where("cand_id = 'A1'"))
    return spark.sql("SELECT n.n_name, m.r AS code, edit_limit(n.n_name, n.n_name) AS most FROM {n} AS n, LATERAL mapping_lookup(n.n_name) AS m", n=corpus.read(spark, d, "nation"))


# ---- lookup, curation and baselines that had no query ----


@query(f"WITH pairs AS ({_CODES}), v AS (SELECT DISTINCT r AS v FROM pairs WHERE cand_id = 'B') SELECT cand_id AS cluster_id, 'r' AS side, count(DISTINCT r) / (SELECT count(*) FROM v) AS containment FROM pairs WHERE r IN (SELECT v FROM v) GROUP BY 1 HAVING count(DISTINCT r) >= 0.9 * (SELECT count(*) FROM v)")
def bitmap_lookup(spark, d):
    """Mappings that hold nine of ten given codes, found through bitmaps before the hash table."""
    pairs = code_pairs(spark, d)
    indexed = stage(apps.index(pairs.withColumnRenamed("cand_id", "cluster_id")), "index")
    asked = pairs.where("cand_id = 'B'").select(F.col("r").alias("v"))
    return apps.lookup_filtered(asked, indexed, apps.index_bits(indexed), 0.9)


@query(f"WITH pairs AS ({_ring(50)}), n AS (SELECT cand_id, count(DISTINCT l) AS hit FROM pairs WHERE CAST(l AS BIGINT) < 100 GROUP BY 1) SELECT cand_id, hit FROM n ORDER BY hit DESC, cand_id LIMIT 10")
def search_raw_tables(spark, d):
    """The ten raw tables that hold most of a hundred given keys: a top-k report."""
    return apps.search_tables(corpus.read(spark, d, "part").where("p_partkey < 100").select(F.col("p_partkey").cast("string").alias("v")), chain(spark, d))


@query("SELECT 'names' AS cluster_id, n_name AS l, r_name AS r FROM nation JOIN region ON n_regionkey = r_regionkey")
def curated_without_numbers(spark, d):
    """Mappings of numbers or times on either side are left out."""
    n = corpus.read(spark, d, "nation").join(corpus.read(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    o = corpus.read(spark, d, "orders")
    maps = [n.select(F.lit("names").alias("cluster_id"), F.col("n_name").alias("l"), F.col("r_name").alias("r")), n.select(F.lit("keys"), F.col("n_name"), F.col("n_nationkey").cast("string")), o.select(F.lit("days"), F.col("o_orderkey").cast("string"), F.col("o_orderdate").cast("string"))]
    return apps.drop_numeric_temporal(maps[0].union(maps[1]).union(maps[2]))


@query(f"WITH rows AS ({_ring(50)}), c AS (SELECT cand_id, domain, ['name','code','id'][CAST(right(cand_id, 2) AS INT) % 3 + 1] AS h FROM rows GROUP BY 1, 2, 3), shared AS (SELECT DISTINCT a.cand_id FROM rows a JOIN c x ON x.cand_id = a.cand_id JOIN rows b ON a.l = b.l AND a.r = b.r AND a.cand_id <> b.cand_id JOIN c y ON y.cand_id = b.cand_id AND y.domain = x.domain AND y.h = x.h) SELECT cand_id, CASE WHEN cand_id IN (SELECT cand_id FROM shared) THEN cand_id ELSE domain || '|' || h || '|brand' END AS cluster_id FROM c")
def hdr_union_disjoint(spark, d):
    """Header unions within a domain where rows must be disjoint."""
    return baselines.header_union(headed(spark, d), "domain", chain(spark, d))
