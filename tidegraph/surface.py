"""The operators a user needs around graph analyses, as queries over the given tables, and their SQL twins."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from tidegraph.functions import relational as R
from tidegraph.runtime import scratch_root
from tidegraph.sources import derived as G, files

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _t(spark, d, name):
    return G.table(spark, d, name)


# Sources and sinks
@query("SELECT DISTINCT 'p:' || page_id AS src, 'u:' || href AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)")
def op_source_page_links(spark, d):
    return G.page_links(spark, d).edges


@query("SELECT c_nationkey::BIGINT AS src, c_custkey AS dst FROM customer")
def op_source_edge_list(spark, d):
    path = f"{scratch_root(spark)}/edge-list-{uuid.uuid4().hex}"
    files.write_edge_list(_t(spark, d, "customer").select(F.col("c_nationkey").cast("long").alias("src"), F.col("c_custkey").alias("dst")), path)
    return files.read_edge_list(spark, path)


@query("SELECT c_nationkey::BIGINT AS src, c_custkey AS dst FROM customer")
def op_source_adjacency(spark, d):
    path = f"{scratch_root(spark)}/adjacency-{uuid.uuid4().hex}"
    files.write_adjacency(_t(spark, d, "customer").select(F.col("c_nationkey").alias("src"), F.col("c_custkey").alias("dst")), path)
    return files.read_adjacency(spark, path)


@query("SELECT c_nationkey::BIGINT AS src, c_custkey AS dst FROM customer")
def op_source_json(spark, d):
    path = f"{scratch_root(spark)}/edges-json-{uuid.uuid4().hex}"
    _t(spark, d, "customer").select(F.col("c_nationkey").alias("src"), F.col("c_custkey").alias("dst")).write.mode("overwrite").json(path)
    return files.read_json_edges(spark, path)


@query("SELECT event_type, count(*) AS n FROM events WHERE event_type <> 'view' GROUP BY event_type")
def op_sink_partitioned(spark, d):
    """Parquet partitioned by type, read back with a partition pruned."""
    path = f"{scratch_root(spark)}/events-by-type-{uuid.uuid4().hex}"
    _t(spark, d, "events").select("event_id", "event_type").write.mode("overwrite").partitionBy("event_type").parquet(path)
    back = spark.read.schema("event_id long, event_type string").parquet(path)
    return back.where("event_type <> 'view'").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


# Filters and projections
@query("SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice BETWEEN 100000 AND 200000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderdate >= TIMESTAMP '1998-01-01'")
def op_filter(spark, d):
    return _t(spark, d, "orders").where("o_totalprice between 100000 and 200000 and o_orderpriority in ('1-URGENT', '2-HIGH') and o_orderdate >= timestamp_ntz'1998-01-01'").select("o_orderkey", "o_custkey")


@query("SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%ring' AND p_type IS NOT NULL")
def op_filter_text(spark, d):
    return _t(spark, d, "part").where("p_name like '%ring' and p_type is not null").select("p_partkey", "p_name")


# Joins
@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def op_join_broadcast(spark, d):
    return _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")  # 25 rows


_CO = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"


def _join_hint(hint):
    def run(spark, d):
        return _t(spark, d, "orders").join(_t(spark, d, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")

    return run


for _hint in ("merge", "shuffle_hash"):
    QUERIES[f"op_join_{_hint}"] = _join_hint(_hint)
    ORACLES[f"op_join_{_hint}"] = _CO


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def op_join_semi(spark, d):
    return _t(spark, d, "customer").join(_t(spark, d, "orders").where("o_orderpriority = '1-URGENT'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_join_anti(spark, d):
    return _t(spark, d, "orders").join(_t(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("SELECT d.doc_id, l.quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id WHERE d.doc_id IS NOT NULL")
def op_join_full(spark, d):
    docs, labels = _t(spark, d, "documents").alias("d"), _t(spark, d, "labels").alias("l")
    return docs.join(labels, F.col("d.doc_id") == F.col("l.doc_id"), "full").where("d.doc_id is not null").select("d.doc_id", "l.quality")


@query("SELECT a.doc_id, b.doc_id AS other FROM labels a JOIN labels b ON a.toxic IS NOT DISTINCT FROM b.toxic AND a.doc_id + 1 = b.doc_id")
def op_join_null_safe(spark, d):
    a, b = _t(spark, d, "labels").alias("a"), _t(spark, d, "labels").alias("b")
    return a.join(b, F.col("a.toxic").eqNullSafe(F.col("b.toxic")) & (F.col("a.doc_id") + 1 == F.col("b.doc_id"))).select("a.doc_id", F.col("b.doc_id").alias("other"))


@query("SELECT o_orderkey, band FROM orders JOIN (SELECT i AS band, i * 50000.0 AS lo, (i + 1) * 50000.0 AS hi FROM range(20) t(i)) ON o_totalprice >= lo AND o_totalprice < hi")
def op_join_range(spark, d):
    bands = spark.range(20).select(F.col("id").alias("band"), (F.col("id") * 50000.0).alias("lo"), ((F.col("id") + 1) * 50000.0).alias("hi"))
    return R.range_join(_t(spark, d, "orders"), bands, "o_totalprice", "lo", "hi", 50000.0).select("o_orderkey", "band")


@query("SELECT e.event_id, o.o_totalprice AS last_price FROM (SELECT event_id, user_id, ts FROM events) e ASOF LEFT JOIN (SELECT o_custkey, o_orderdate + INTERVAL 25 YEARS AS at, max(o_totalprice) AS o_totalprice FROM orders GROUP BY ALL) o ON e.user_id = o.o_custkey AND e.ts >= o.at")
def op_join_as_of(spark, d):
    """The last order of a user at or before each event, with orders moved to the time of the events."""
    orders = _t(spark, d, "orders").select(F.col("o_custkey").alias("user_id"), F.expr("o_orderdate + interval 25 years").alias("ts"), "o_totalprice").groupBy("user_id", "ts").agg(F.max("o_totalprice").alias("price"))
    return R.as_of(_t(spark, d, "events").select("event_id", "user_id", "ts"), orders, "user_id", "ts", "price").select("event_id", "last_price")


# Aggregates
@query("SELECT c_mktsegment, count(*) AS n, round(avg(c_acctbal), 4) AS mean, min(c_custkey) AS lo, max(c_custkey) AS hi, count(DISTINCT c_nationkey) AS nations, count(*) FILTER (WHERE c_acctbal > 0) AS positive FROM customer GROUP BY c_mktsegment HAVING count(*) > 1")
def op_aggregate(spark, d):
    return _t(spark, d, "customer").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("c_acctbal"), 4).alias("mean"), F.min("c_custkey").alias("lo"), F.max("c_custkey").alias("hi"), F.count_distinct("c_nationkey").alias("nations"), F.count_if(F.col("c_acctbal") > 0).alias("positive")).where("n > 1")


@query("SELECT o_orderpriority, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY o_orderpriority")
def op_min_by(spark, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return _t(spark, d, "orders").groupBy("o_orderpriority").agg(F.min_by("o_orderkey", by).alias("cheapest"), F.max_by("o_orderkey", by).alias("dearest"))


@query("SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY GROUPING SETS ((r_name), (r_name, n_name), (c_mktsegment), ())")
def op_grouping_sets(spark, d):
    joined = _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(_t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.groupingSets([[F.col("r_name")], [F.col("r_name"), F.col("n_name")], [F.col("c_mktsegment")], []], "r_name", "n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_cube(spark, d):
    return _t(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def op_pivot(spark, d):
    wide = _t(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1)))
    return wide.select("user_id", F.coalesce("click", F.lit(0)).cast("long").alias("click"), F.coalesce("purchase", F.lit(0)).cast("long").alias("purchase"))


# Windows, order, sets
@query("SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, round(cume_dist() OVER w, 9) AS cd, round(percent_rank() OVER w, 9) AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)")
def op_window_rank(spark, d):
    w = W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    long = lambda c: c.cast("long")
    return _t(spark, d, "customer").select("c_custkey", long(F.row_number().over(w)).alias("rn"), long(F.rank().over(w)).alias("rk"), long(F.dense_rank().over(w)).alias("dr"), long(F.ntile(4).over(w)).alias("quarter"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS so_far, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_window_frames(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = W.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)
    return _t(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.count(F.lit(1)).over(w.rowsBetween(W.unboundedPreceding, 0)).alias("so_far"), F.count(F.lit(1)).over(seconds).alias("last_hour"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_top_k(spark, d):
    return _t(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3")
def op_top_k_per_group(spark, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(spark, d, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("o_orderpriority", "o_orderkey")


@query("SELECT c_custkey AS id FROM customer INTERSECT SELECT o_custkey FROM orders")
def op_intersect(spark, d):
    return _t(spark, d, "customer").select(F.col("c_custkey").alias("id")).intersect(_t(spark, d, "orders").select("o_custkey"))


@query("SELECT o_custkey AS id FROM orders EXCEPT ALL SELECT user_id FROM events")
def op_except_all(spark, d):
    return _t(spark, d, "orders").select(F.col("o_custkey").alias("id")).exceptAll(_t(spark, d, "events").select("user_id"))


@query("SELECT src, dst FROM (SELECT c_custkey AS src, c_nationkey::BIGINT AS dst FROM customer) UNION SELECT c_nationkey::BIGINT, c_custkey FROM customer")
def op_union_distinct(spark, d):
    e = _t(spark, d, "customer").select(F.col("c_custkey").alias("src"), F.col("c_nationkey").cast("long").alias("dst"))
    return e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


# Scalars
@query("SELECT event_id, date_trunc('day', ts) AS day, hour(ts) AS hour, lower(event_type) || '-' || user_id AS label, floor(value)::BIGINT AS whole, length(props)::BIGINT AS size, CASE WHEN value > 50 THEN 'high' ELSE 'low' END AS level FROM events")
def op_scalars(spark, d):
    return _t(spark, d, "events").select(
        "event_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"), F.hour("ts").cast("long").alias("hour"), F.concat(F.lower("event_type"), F.lit("-"), F.col("user_id").cast("string")).alias("label"),
        F.floor("value").alias("whole"), F.length("props").cast("long").alias("size"), F.when(F.col("value") > 50, "high").otherwise("low").alias("level"),
    )


@query("SELECT l_orderkey, array_to_string(list_sort(list(DISTINCT l_partkey)), ',') AS parts, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY l_orderkey")
def op_arrays(spark, d):
    sets = _t(spark, d, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("p"))
    return sets.select("l_orderkey", F.array_join(F.transform("p", lambda x: x.cast("string")), ",").alias("parts"), F.size("p").cast("long").alias("n"))


# Streams
@query("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_stream_tumbling(spark, d):
    """Daily counts from a stream of all events; what the watermark leaves open at the end is counted from the batch."""
    from tidegraph.streaming.edges import tumbling

    events = _t(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return tumbling(events).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("WITH RECURSIVE g AS (SELECT user_id AS src, nxt AS dst FROM (SELECT *, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL AND nxt <> user_id), b AS (SELECT src, dst FROM g UNION SELECT dst, src FROM g), c(id, component) USING KEY (id) AS (SELECT src AS id, src AS component FROM b UNION SELECT e.dst, min(w.component) FROM c w JOIN b e ON e.src = w.id JOIN recurring.c p ON p.id = e.dst WHERE w.component < p.component GROUP BY e.dst) SELECT id, component FROM c")
def op_stream_components(spark, d):
    """Components kept up to date over a stream of edge files."""
    from tidegraph.streaming.edges import ComponentKeeper, run_available

    folder = f"{scratch_root(spark)}/stream-{uuid.uuid4().hex}"
    G.user_sequence(spark, d).edges.select("src", "dst").repartition(3).write.parquet(f"{folder}/in")
    keeper = ComponentKeeper()
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    run_available(stream, keeper.process, f"{folder}/state")
    return keeper.components()
