"""Supporting relational and streaming queries, each with its DuckDB equivalent."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mapforge import streaming
from mapforge.sources import corpus

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        Q[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping(o_orderstatus) + grouping(o_orderpriority) AS BIGINT) AS level FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def rel_rollup(spark, d):
    level = (F.grouping("o_orderstatus") + F.grouping("o_orderpriority")).cast("long")
    return corpus.read(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), level.alias("level"))


@query("SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS f, count(*) FILTER (l_linestatus = 'O') AS o FROM lineitem GROUP BY 1")
def rel_pivot(spark, d):
    counts = corpus.read(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return counts.select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("SELECT n_name, r_name, count(c_custkey) AS n FROM nation JOIN region ON n_regionkey = r_regionkey LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1, 2")
def rel_star_join(spark, d):
    """Customers are counted by key before the join, so only one row a nation meets the dimensions."""
    n = corpus.read(spark, d, "customer").groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(F.count("c_custkey").alias("n"))
    named = corpus.read(spark, d, "nation").join(corpus.read(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return named.join(n, "n_nationkey", "left").select("n_name", "r_name", F.coalesce("n", F.lit(0)).alias("n"))


@query("SELECT c_mktsegment, count(*) AS n FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'O') GROUP BY 1")
def rel_semi_join(spark, d):
    open_ = corpus.read(spark, d, "orders").where("o_orderstatus = 'O'").select(F.col("o_custkey").alias("c_custkey"))
    return corpus.read(spark, d, "customer").join(open_, "c_custkey", "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT coalesce(c_nationkey, s_nationkey) AS nationkey, nc, ns FROM (SELECT c_nationkey, count(*) AS nc FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS ns FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")
def rel_full_join(spark, d):
    c = corpus.read(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nationkey")).agg(F.count("*").alias("nc"))
    s = corpus.read(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nationkey")).agg(F.count("*").alias("ns"))
    return c.join(s, "nationkey", "full")


@query("SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def rel_range_join(spark, d):
    """Later events of a user within half an hour: bins of that width turn the range into equal keys."""
    e = corpus.read(spark, d, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_800_000_000).alias("bin"))
    a = e.withColumn("bin", F.explode(F.array("bin", F.col("bin") + 1)))
    b = e.select(F.col("event_id").alias("other"), "user_id", F.col("ts").alias("ts2"), "bin")
    return a.join(b, ["user_id", "bin"]).where("event_id <> other and ts2 > ts and ts2 <= ts + interval 30 minutes").select("event_id", "other")


@query("WITH p AS (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) SELECT e.event_id, p.event_id AS last_purchase FROM events e ASOF LEFT JOIN p ON e.user_id = p.user_id AND e.ts >= p.ts")
def rel_asof_join(spark, d):
    """The last purchase of a user up to each event: one window over the table itself, no join."""
    bought = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    upto = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return corpus.read(spark, d, "events").select("event_id", F.max(bought).over(upto)["event_id"].alias("last_purchase"))


@query("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, lag(o_orderkey) OVER v AS prev, round(sum(o_totalprice) OVER (v ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def rel_windows(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    own = [F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.lag("o_orderkey").over(w).alias("prev")]
    running = F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running")
    return corpus.read(spark, d, "orders").select("o_orderkey", *own, running)


@query("(SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier) EXCEPT SELECT n_nationkey FROM nation WHERE n_regionkey = 0")
def rel_set_ops(spark, d):
    c, s = corpus.read(spark, d, "customer").select(F.col("c_nationkey").alias("k")), corpus.read(spark, d, "supplier").select("s_nationkey")
    return c.intersect(s).subtract(corpus.read(spark, d, "nation").where("n_regionkey = 0").select("n_nationkey"))


@query("SELECT year(o_orderdate) AS y, quarter(o_orderdate) AS q, count(*) AS n, CAST(max(datediff('day', date_trunc('quarter', o_orderdate), o_orderdate)) AS BIGINT) AS last_day FROM orders GROUP BY 1, 2")
def rel_dates(spark, d):
    day = F.datediff("o_orderdate", F.date_trunc("quarter", F.col("o_orderdate").cast("timestamp")))
    o = corpus.read(spark, d, "orders").select(F.year("o_orderdate").cast("long").alias("y"), F.quarter("o_orderdate").cast("long").alias("q"), day.alias("day"))
    return o.groupBy("y", "q").agg(F.count("*").alias("n"), F.max("day").cast("long").alias("last_day"))


@query("SELECT event_type, CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k, count(*) AS n FROM events GROUP BY 1, 2")
def rel_json(spark, d):
    return corpus.read(spark, d, "events").groupBy("event_type", F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))


@query("SELECT p_brand, array_to_string(list_sort(list(DISTINCT p_size)), ',') AS sizes, max_by(p_partkey, (p_retailprice, p_partkey)) AS dearest FROM part GROUP BY 1")
def rel_arrays(spark, d):
    sizes = F.array_join(F.transform(F.sort_array(F.collect_set("p_size")), lambda x: x.cast("string")), ",")
    return corpus.read(spark, d, "part").groupBy("p_brand").agg(sizes.alias("sizes"), F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("dearest"))


@query("SELECT o_orderkey, n_name AS filled FROM orders LEFT JOIN customer ON o_custkey = c_custkey LEFT JOIN nation ON c_nationkey = n_nationkey")
def stream_fill(spark, d):
    """Arriving orders get the nation that the mapping from customers holds: a stream joined with a table."""
    cust, nation = corpus.read(spark, d, "customer"), corpus.read(spark, d, "nation")
    mapping = cust.join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("o_custkey"), F.col("n_name").alias("filled"))
    filled = streaming.table_stream(spark, d, "orders").join(mapping, "o_custkey", "left").select("o_orderkey", "filled")
    return streaming.run_to_table(spark, filled, "fill")
