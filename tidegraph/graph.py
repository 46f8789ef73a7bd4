"""Property graphs: a vertex and an edge DataFrame with a declared shape."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, functions as F


def between(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """The edges of which both ends are in ``ids(id)``."""
    kept = edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return kept.select(*edges.columns)


@dataclass
class PropertyGraph:
    """``vertices(id, ...)`` with unique ids and ``edges(src, dst, ...)``; undirected graphs hold both orientations.

    ``dst_in_vertices`` records that every edge target is a vertex, which join elimination relies on; ``check_integrity``
    finds it out, derivations that guarantee it set it. ``simple`` likewise records that no edge is held twice.
    ``once`` holds the edges it belongs to and what writes each of them once, see ``halves``.
    """

    vertices: DataFrame
    edges: DataFrame
    directed: bool = True
    dst_in_vertices: bool = False
    simple: bool = False
    once: tuple[DataFrame, Callable[[], DataFrame | None]] | None = None

    @staticmethod
    def of_edges(edges: DataFrame, directed: bool = True) -> PropertyGraph:
        """The graph whose vertices are the ends of ``edges``."""
        ids = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id"))).distinct()
        return PropertyGraph(ids, edges, directed, True)

    def halves(self) -> DataFrame | None:
        """Each edge of a simple undirected graph once, as written ``(src, dst)`` with src < dst, where the derivation of these edges has a way to."""
        return self.once[1]() if self.once is not None and self.once[0] is self.edges else None

    def distinct(self, keep: str = "distinct", weight: str = "weight") -> PropertyGraph:
        """Without parallel edges: bare pairs, or with the least ``weight`` of each pair (``keep='min_weight'``)."""
        if keep == "keep":
            return self
        if keep == "min_weight":
            return replace(self, edges=self.edges.groupBy("src", "dst").agg(F.min(weight).alias(weight)))
        return replace(self, edges=self.edges.select("src", "dst").distinct(), simple=True)

    def without_loops(self) -> PropertyGraph:
        return replace(self, edges=self.edges.where("src <> dst"))

    def symmetrised(self) -> PropertyGraph:
        """Both orientations of every edge, once each."""
        pairs = self.edges.select("src", "dst")
        if self.simple and not self.directed:
            return replace(self, edges=pairs)
        both = pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
        return replace(self, edges=both, directed=False, simple=True)

    def reversed(self) -> PropertyGraph:
        others = [c for c in self.edges.columns if c not in ("src", "dst")]
        return replace(self, edges=self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *others), dst_in_vertices=False)

    def subgraph(self, vertex: Column | str | None = None, edge: Column | str | None = None) -> PropertyGraph:
        """The graph of the vertices and edges that satisfy the predicates; edges keep only selected ends.

        Predicates are applied to the scans, where they can be pushed down; ends are checked by two semi joins.
        """
        edges = self.edges if edge is None else self.edges.where(edge)
        if vertex is None:
            return replace(self, edges=edges)
        vertices = self.vertices.where(vertex)
        ids = vertices.select("id")
        return replace(self, vertices=vertices, edges=between(edges, ids), dst_in_vertices=True)

    def narrow(self, *edge_columns: str) -> PropertyGraph:
        """Ids and ends only (and ``edge_columns``), so that iterations carry no attributes."""
        return replace(self, vertices=self.vertices.select("id"), edges=self.edges.select("src", "dst", *edge_columns))

    def check_integrity(self) -> DataFrame:
        """One row: ``vertices, edges, null_ids, duplicate_ids, null_ends, dangling_src, dangling_dst``."""
        v, e = self.vertices.select("id"), self.edges.select("src", "dst")
        ids = v.agg(F.count(F.lit(1)).alias("vertices"), F.count_if(F.col("id").isNull()).alias("null_ids"), (F.count("id") - F.count_distinct("id")).alias("duplicate_ids"))
        ends = e.agg(F.count(F.lit(1)).alias("edges"), F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("null_ends"))
        out = ids.crossJoin(F.broadcast(ends))
        for end in ("src", "dst"):
            loose = e.where(F.col(end).isNotNull()).join(v.withColumnRenamed("id", end), end, "left_anti").agg(F.count(F.lit(1)).alias(f"dangling_{end}"))
            out = out.crossJoin(F.broadcast(loose))
        return out.select("vertices", "edges", "null_ids", "duplicate_ids", "null_ends", "dangling_src", "dangling_dst")
