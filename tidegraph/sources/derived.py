"""Graphs derived from the star-schema, event and text tables. All windows are partitioned."""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.operators.blocks import is_banded
from tidegraph.sources.baskets import item_pairs

SUPPLIER_OFFSET = 1_000_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _chain(rows: DataFrame, end: str, parts: list, order: list, weight: str, created: str, etype: str, extra: tuple[str, ...] = ()) -> DataFrame:
    """An edge from each row's ``end`` to that of the next row of its partition; loops are left out."""
    chained = rows.withColumn("dst", F.lead(end).over(W.partitionBy(*parts).orderBy(*order)))
    return chained.where(F.col("dst").isNotNull() & (F.col("dst") != F.col(end))).select(
        F.col(end).cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col(weight).cast("decimal(18,2)").alias("weight"), F.col(created).alias("created"), F.col(etype).alias("etype"), *extra
    )


def handoff(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Customer of an order -> customer of the next order of the same date; weighted, timed and typed."""
    edges = _chain(table(spark, sf_dir, "orders"), "o_custkey", ["o_orderdate"], ["o_orderkey"], "o_totalprice", "o_orderdate", "o_orderpriority", ("o_orderstatus",))
    vertices = table(spark, sf_dir, "customer").withColumnRenamed("c_custkey", "id")
    return PropertyGraph(vertices, edges, True, True)


def co_purchase(spark: SparkSession, sf_dir: str, sliced: bool = False) -> PropertyGraph:
    """Parts bought in one order, both orientations; vertices are all parts. ``sliced``, for tests: urgent orders of the year 2000 only, vertices are the ends."""
    # Dealt out by order first, so that lines move once: copies drop out and pairs are made where they lie.
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").where("l_orderkey is not null").repartition("l_orderkey").distinct()
    if sliced:
        orders = table(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT' and o_orderdate >= timestamp_ntz'2000-01-01' and o_orderdate < timestamp_ntz'2001-01-01'")
        lines = lines.join(orders.select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey", "left_semi")
    other = lines.select("l_orderkey", F.col("l_partkey").alias("dst"))
    # One orientation goes through the shuffle.
    pairs = lines.join(other, "l_orderkey").where("l_partkey < dst").select(F.col("l_partkey").alias("src"), "dst").distinct()
    edges = pairs.select(F.inline(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))))
    vertices = edges.select(F.col("src").alias("id")).distinct() if sliced else table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
    baskets = lines.select(F.col("l_orderkey").alias("basket"), F.col("l_partkey").alias("item"))
    if not sliced:
        baskets = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("basket"), F.col("l_partkey").alias("item"))
    once = (edges, cache(lambda: item_pairs(baskets))) if is_banded(edges) else None
    return PropertyGraph(vertices, edges, False, True, simple=True, once=once)


def user_sequence(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """User of an event -> user of the next event of the same hour."""
    events = table(spark, sf_dir, "events").withColumn("hour", F.date_trunc("hour", "ts"))
    return PropertyGraph.of_edges(_chain(events, "user_id", ["hour"], ["ts", "event_id"], "value", "ts", "event_type"))


def trade(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Customer -> supplier of any of its orders' lines; supplier ids are offset."""
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), (F.col("l_suppkey") + SUPPLIER_OFFSET).alias("dst")).distinct()
    edges = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("src")).join(lines, "o_orderkey").select("src", "dst").distinct()
    return PropertyGraph.of_edges(edges)


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(user, item, rating)``: customer, part and the mean quantity bought."""
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return orders.join(lines, "o_orderkey").groupBy(F.col("o_custkey").alias("user"), F.col("l_partkey").alias("item")).agg(F.avg("l_quantity").alias("rating"))


def page_links(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Page -> link target, string keys, bipartite."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    edges = pages.select(F.concat(F.lit("p:"), "page_id").alias("src"), F.concat(F.lit("u:"), "href").alias("dst")).distinct()
    return PropertyGraph.of_edges(edges)


def duplicates(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Documents of equal text, each linked with the smallest of them; vertices are all documents with their labels.

    A star connects a group of copies as a clique does, with as many edges as copies.
    """
    docs = table(spark, sf_dir, "documents").where("text is not null").select(F.col("doc_id").alias("id"), F.sha2("text", 256).alias("h"))
    first = docs.groupBy("h").agg(F.min("id").alias("dst"))
    edges = docs.join(first, "h").where("id <> dst").select(F.col("id").alias("src"), "dst")
    labels = table(spark, sf_dir, "labels").withColumnRenamed("doc_id", "id")
    vertices = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id")).join(labels, "id", "left")
    return PropertyGraph(vertices, edges, False, True)


def replies(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Turn -> next turn of a conversation; id = conversation * 1000 + turn."""
    turns = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "conv_id", "turn", "role")
    edges = turns.select(F.col("id").alias("src"), F.lead("id").over(W.partitionBy("conv_id").orderBy("turn")).alias("dst")).where("dst is not null")
    return PropertyGraph(turns, edges, True, True)


def geography(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Region -> nation -> customer and supplier; ids are offset by level."""
    level = 10**10
    nation, customer, supplier = (table(spark, sf_dir, t) for t in ("nation", "customer", "supplier"))
    edges = nation.select(F.col("n_regionkey").cast("long").alias("src"), (F.col("n_nationkey") + level).alias("dst"), F.lit("nation").alias("etype"))
    edges = edges.unionByName(customer.select((F.col("c_nationkey") + level).alias("src"), (F.col("c_custkey") + 2 * level).alias("dst"), F.lit("customer").alias("etype")))
    edges = edges.unionByName(supplier.select((F.col("s_nationkey") + level).alias("src"), (F.col("s_suppkey") + 3 * level).alias("dst"), F.lit("supplier").alias("etype")))
    return PropertyGraph.of_edges(edges)


#: Vectors of a block; every pair of blocks is compared in a task of its own.
VECTOR_BLOCK = 2_048


def embedding_neighbours(spark: SparkSession, sf_dir: str, least: float = 0.3, block: int = VECTOR_BLOCK) -> PropertyGraph:
    """Vectors connected by cosine similarities of ``least`` or more: the edges span each component, and are not all its pairs.

    Every pair of blocks is compared, as no index reaches all pairs at a similarity this low; the work grows with the
    square of the vectors. A pair of blocks gives at most as many edges as it has vectors.
    """
    vectors = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    count = max(1, -(-vectors.count() // block))
    dealt = (
        vectors.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(count)).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(count - 1))))
        .select("id", "v", F.least("own", "other").alias("one"), F.greatest("own", "other").alias("two"))
    )
    near = dealt.groupBy("one", "two").applyInArrow(_spanning_pairs(least), "src long, dst long")
    return PropertyGraph(vectors.select("id"), near, False, True).symmetrised()


def _spanning_pairs(least: float):
    def compare(rows):
        import numpy as np
        import pyarrow as pa

        ids = rows["id"].to_numpy()
        vectors = np.array(rows["v"].to_pylist(), dtype=np.float64)
        size = np.sqrt((vectors * vectors).sum(1))
        unseen, src, dst = np.ones(len(ids), dtype=bool), [], []
        for start in range(len(ids)):
            if not unseen[start]:
                continue
            unseen[start], waiting = False, [start]
            while waiting:
                i = waiting.pop()
                found = np.flatnonzero(unseen & (vectors @ vectors[i] >= least * size * size[i]))
                unseen[found] = False
                waiting += found.tolist()
                src += [ids[i]] * len(found)
                dst += ids[found].tolist()
        return pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64())})

    return compare
