"""One-hop neighbourhood analyses as joins: triangles, clustering, strong overlap, weak ties, degrees."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.operators import blocks
from tidegraph.runtime import materialize


def degrees(graph: PropertyGraph) -> DataFrame:
    """``(id, out_degree, in_degree, degree)`` of every vertex, zeros included; parallel edges count."""
    ends = graph.edges.select(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(graph.edges.select(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    sums = ends.groupBy("id").agg(F.sum("o").alias("o"), F.sum("i").alias("i"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return graph.vertices.select("id").join(sums, "id", "left").select("id", zero("o").alias("out_degree"), zero("i").alias("in_degree"), (zero("o") + zero("i")).alias("degree"))


def oriented(graph: PropertyGraph, orient: str = "degree") -> DataFrame:
    """Each undirected edge once, from its lower to its higher end by id or by (degree, id): no vertex keeps many out-edges."""
    pairs = graph.symmetrised().edges.where("src <> dst")
    if orient == "id":
        return pairs.where("src < dst")
    degree = pairs.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    both = pairs.join(degree.withColumnRenamed("d", "ds"), "src").join(degree.select(F.col("src").alias("dst"), F.col("d").alias("dd")), "dst")
    return both.where("ds < dd or (ds = dd and src < dst)").select("src", "dst")


def triangles(graph: PropertyGraph, orient: str = "degree") -> DataFrame:
    """``(a, b, c)`` of every triangle once: wedges from the lowest vertex, closed by a join on two keys."""
    e = oriented(graph, orient)
    first, second = e.select(F.col("src").alias("a"), F.col("dst").alias("b")), e.select(F.col("src").alias("a"), F.col("dst").alias("c"))
    closing = e.select(F.col("src").alias("b"), F.col("dst").alias("c"))
    return first.join(second, "a").where("b <> c").join(closing, ["b", "c"]).select("a", "b", "c")


def triangle_count(graph: PropertyGraph, per_vertex: bool = False, orient: str = "degree") -> DataFrame:
    """One row ``triangles``, or ``(id, triangles)`` of every vertex. Blocks of edges are closed as arrays where ids are whole numbers."""
    counts, _ = _per_vertex(graph, orient)
    if not per_vertex:
        return counts.agg(F.expr("coalesce(sum(triangles), 0) div 3").alias("triangles"))
    return graph.vertices.select("id").join(counts, "id", "left").select("id", F.coalesce("triangles", F.lit(0)).cast("long").alias("triangles"))


def _per_vertex(graph: PropertyGraph, orient: str = "degree") -> tuple[DataFrame, DataFrame]:
    """``(id, triangles)`` of the vertices in a triangle, and the undirected edges once each as ``(src, dst)``."""
    halves = graph.halves()
    if halves is not None:
        return blocks.triangle_counts(halves, orient, True) or (halves.select(F.col("src").alias("id"), F.lit(0).cast("long").alias("triangles")).limit(0), halves)
    found = blocks.triangle_counts(graph.edges.select("src", "dst") if graph.directed or not graph.simple else graph.edges.where("src < dst"), orient) if blocks.is_banded(graph.edges) else None
    if found is not None:
        counts, pairs = found
        return counts, pairs if graph.simple and not graph.directed else pairs.distinct()
    counts = triangles(graph, orient).select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("triangles"))
    return counts, graph.symmetrised().edges.where("src < dst")


def _with_degrees(graph: PropertyGraph) -> DataFrame:
    """``(id, d, triangles)`` of the vertices with a neighbour: how many neighbours, and how many pairs of them are joined."""
    counts, pairs = _per_vertex(graph)
    ends = pairs.select(F.explode(F.array("src", "dst")).alias("id"))
    return ends.groupBy("id").agg(F.count(F.lit(1)).alias("d")).join(counts, "id", "left").select("id", "d", F.coalesce("triangles", F.lit(0)).cast("long").alias("triangles"))


def clustering(graph: PropertyGraph) -> DataFrame:
    """``(id, coefficient)``: triangles over wedges at each vertex, 0 without wedges."""
    joined = graph.vertices.select("id").join(_with_degrees(graph), "id", "left")
    return joined.select("id", F.when(F.col("d") > 1, 2 * F.col("triangles") / (F.col("d") * (F.col("d") - 1))).otherwise(0.0).alias("coefficient"))


def estimated_triangles(graph: PropertyGraph, share: float = 0.1, seed: int = 3) -> DataFrame:
    """An estimate from a sample of edges, each kept with probability ``share``: a sampling operator."""
    e = oriented(graph, "id").where(F.pmod(F.xxhash64("src", "dst", F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000))
    sampled = PropertyGraph(graph.vertices, e, True, graph.dst_in_vertices)
    return triangle_count(sampled, orient="id").select((F.col("triangles") / share**3).alias("triangles"))


def strong_overlap(graph: PropertyGraph, threshold: float, strict: bool = True, measure: str = "count") -> DataFrame:
    """``(n1, n2, common)`` of vertex pairs n1 < n2 whose shared out-neighbours pass ``threshold``; ``value`` for other measures.

    ``measure``: 'count' (parallel edges count), 'jaccard', 'cosine', 'min' (over the smaller neighbourhood) or 'adamic'
    (common neighbours weighted by 1 / log in-degree). ``strict``: above the threshold, else at least it. Where ids are whole
    numbers, blocks of sources are multiplied as arrays and only pairs that pass leave a task.
    """
    passes = lambda c: c > threshold if strict else c >= threshold
    over = {
        "jaccard": lambda common, d1, d2, least, root: common / (d1 + d2 - common),
        "cosine": lambda common, d1, d2, least, root: common / root(d1 * d2),
        "min": lambda common, d1, d2, least, root: common / least(d1, d2),
    }.get(measure)
    e = graph.edges.select("src", "dst")
    found = None
    if blocks.is_banded(e):
        keep = {"count": lambda common, value, d1, d2: passes(common), "adamic": lambda common, value, d1, d2: passes(value)}.get(measure) or (lambda common, value, d1, d2: passes(over(common, d1, d2, np.minimum, np.sqrt)))
        simple, halves = graph.simple, graph.halves()
        both = (lambda kept: kept) if halves is None else both_ways
        weights = (lambda kept: _rarity(both(kept) if simple else kept.distinct())) if measure == "adamic" else None
        least = max(1, math.floor(threshold)) if measure == "count" else 1
        found = blocks.common_neighbours(e if halves is None else halves, keep, least, measure != "count", weights, halves is not None)
    if found is not None:
        if over is None:
            pairs = found.where("n2 is not null").withColumnRenamed("value", "sw")
        else:
            found = materialize(found, "overlap", free=True).df
            pairs, size = found.where("n2 is not null"), found.where("n2 is null").select(F.col("n1").alias("src"), F.col("common").alias("d"))
    else:
        e = e if measure == "count" else e.distinct()
        weighed = e.join(_rarity(e), "dst") if measure == "adamic" else e.withColumn("w", F.lit(1.0))
        one, two = weighed.select(F.col("src").alias("n1"), "dst", "w"), e.select(F.col("src").alias("n2"), "dst")
        pairs = one.join(two, "dst").where("n1 < n2").groupBy("n1", "n2").agg(F.count(F.lit(1)).alias("common"), F.sum("w").alias("sw"))
        size = e.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    if measure == "count":
        return pairs.where(passes(F.col("common"))).select("n1", "n2", "common")
    if measure == "adamic":
        return pairs.select("n1", "n2", "common", F.col("sw").alias("value")).where(passes(F.col("value")))
    sized_pairs = pairs.select("n1", "n2", "common").join(size.select(F.col("src").alias("n1"), F.col("d").alias("d1")), "n1").join(size.select(F.col("src").alias("n2"), F.col("d").alias("d2")), "n2")
    return sized_pairs.select("n1", "n2", "common", over(F.col("common"), F.col("d1"), F.col("d2"), F.least, F.sqrt).alias("value")).where(passes(F.col("value")))


def both_ways(halves: DataFrame) -> DataFrame:
    """Each of ``halves(src, dst)`` and its reverse."""
    return halves.select(F.inline(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))))


def _rarity(edges: DataFrame) -> DataFrame:
    """``(dst, w)``: one over the logarithm of the in-degree and one."""
    return edges.groupBy("dst").agg((1 / F.log(F.count(F.lit(1)) + 1.0)).alias("w"))


def weak_ties(graph: PropertyGraph, threshold: int, strict: bool = True, form: str = "anti") -> DataFrame:
    """``(id, pairs)`` of vertices between more than ``threshold`` (``strict``; else at least) pairs that no edge closes.

    A pair is an in-neighbour and an out-neighbour of the vertex that differ and are not joined by an edge that leads from
    the out-neighbour back to the in-neighbour. On undirected graphs each unordered pair counts once. ``form``: 'left' and 'anti' look for the closing edge
    by an outer or an anti join; 'identity' (undirected, no parallel edges) subtracts the triangles at a vertex from its wedges.
    On simple undirected graphs with whole-number ids every form looks for closing edges in blocks and makes no wedge a row.
    """
    passes = (F.col("pairs") > threshold) if strict else (F.col("pairs") >= threshold)
    if form == "identity" and graph.directed:
        raise ValueError("the identity holds on undirected graphs")
    if form == "identity" or (graph.simple and not graph.directed and blocks.is_banded(graph.edges)):
        return _with_degrees(graph).select("id", (F.expr("d * (d - 1) div 2") - F.col("triangles")).alias("pairs")).where(passes)
    e = graph.edges.select("src", "dst")
    wedges = e.select(F.col("src").alias("a"), F.col("dst").alias("id")).join(e.select(F.col("src").alias("id"), F.col("dst").alias("b")), "id").where("a <> b")
    closing = e.distinct().select(F.col("dst").alias("a"), F.col("src").alias("b"))
    if form == "left":
        marked = wedges.join(closing.withColumn("closed", F.lit(1)), ["a", "b"], "left")
        counts = marked.groupBy("id").agg(F.count_if(F.col("closed").isNull()).alias("n"))
    else:
        counts = wedges.join(closing, ["a", "b"], "left_anti").groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    pairs = F.col("n") if graph.directed else F.expr("n div 2")
    return counts.select("id", pairs.cast("long").alias("pairs")).where(passes)


def predicted_wedges(graph: PropertyGraph) -> DataFrame:
    """One row ``(wedges, ids_sent)``: the rows a one-hop join makes and the ids the message form sends, before either is run."""
    ends = degrees(graph)
    return ends.agg(F.sum(F.col("in_degree") * F.col("out_degree")).alias("wedges"), F.sum(F.col("out_degree") * F.col("out_degree")).alias("ids_sent"))
