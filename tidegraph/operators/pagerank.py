"""PageRank as a relational loop: share of each source, sum by target, affine map."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.plans.iterate import RunReport
from tidegraph.plans.layout import DealtEdges, keyed, parts_for
from tidegraph.runtime import materialize


def pagerank(
    graph: PropertyGraph,
    rounds: int = 10,
    damping: float = 0.85,
    sources: str = "standard",
    tol: float | None = None,
    weight: str | None = None,
    source_ids: list | None = None,
    eliminate_join: bool | None = None,
    checkpoint_every: int = 5,
    cached: bool = True,
    report: RunReport | None = None,
) -> DataFrame:
    """``(id, rank)`` after ``rounds`` rounds, or earlier once no rank moves by ``tol``.

    ``sources``: 'standard' keeps every vertex at its base rank at least; 'literal' keeps only vertices with in-edges, as
    inner joins do; 'redistribute' also spreads the rank of vertices without out-edges, so ranks sum to one.
    ``source_ids`` restarts there only. Parallel edges count as often as they are; ``weight`` names a column to share by.
    The join with target vertices is left out where every target is known to be a vertex (``eliminate_join`` overrides).
    One shuffle a round, of sums combined by task, besides the co-partitioned vertex join. ``cached=False`` scans the edges
    as they lie in every round, for copies bucketed by source. With a ``report`` every round is written by itself, and gets
    its seconds there.
    """
    ids = graph.vertices.select("id")
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    edges = DealtEdges(graph.edges.select("src", "dst", w.alias("w")), cached)
    out = edges.df.groupBy("src").agg(F.sum("w").alias("out"))
    n = ids.count()
    base = F.lit(1.0 / n if n else 0.0)
    if source_ids is not None:
        base = F.when(F.col("id").isin(source_ids), 1.0 / max(1, len(source_ids))).otherwise(0.0)
    degrees = keyed(ids.select("id", base.alias("base")).join(out.withColumnRenamed("src", "id"), "id", "left"), "id", parts_for(n, int(ids.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    rank = degrees.select("id", F.col("base").alias("rank"))
    keep_join = not graph.dst_in_vertices if eliminate_join is None else not eliminate_join
    scratch = None
    for k in range(1, rounds + 1):
        began = report.begin_round(ids.sparkSession, k) if report is not None else 0.0
        share = rank.join(degrees.where("out > 0").select("id", "out"), "id").select(F.col("id").alias("src"), (F.col("rank") / F.col("out")).alias("share"))
        moved = edges.meet(share)
        if keep_join:
            moved = moved.join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
        sums = moved.groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("share") * F.col("w")).alias("s"))
        if sources == "literal":
            after = sums.join(degrees.select("id", "base"), "id").select("id", (F.col("base") * (1 - damping) + damping * F.col("s")).alias("rank"))
        else:
            joined = degrees.select("id", "base").join(sums, "id", "left")
            gained = F.coalesce("s", F.lit(0.0))
            if sources == "redistribute":
                loose = rank.join(degrees.where("out is null").select("id"), "id", "left_semi").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("loose"))
                joined = joined.crossJoin(F.broadcast(loose))  # one row
                gained = gained + F.col("loose") * F.col("base")
            after = joined.select("id", (F.col("base") * (1 - damping) + damping * gained).alias("rank"))
        if tol is not None or k % checkpoint_every == 0 or k == rounds or sources == "redistribute" or report is not None:
            if tol is not None:
                seen = Observation()
                old = rank.withColumnRenamed("rank", "old")
                after = after.join(old, "id").observe(seen, F.max(F.abs(F.col("rank") - F.col("old"))).alias("moved")).select("id", "rank")
            written = materialize(after, "rank")
            if report is not None:
                report.rounds.append({"round": k, "seconds": time.time() - began, "updates": n, "applied": "replace"})
            moved_by = seen.get["moved"] if tol is not None else None
            if scratch is not None:
                scratch.drop()
            scratch, after = written, written.df
        rank = after
        if tol is not None and (moved_by is None or moved_by <= tol):
            break
    edges.unpersist()
    degrees.unpersist()
    return rank
