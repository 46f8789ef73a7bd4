"""Connected components by label propagation: minimum of neighbours' labels, in several directions."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.operators.components import star_components
from tidegraph.plans.iterate import BROADCAST_ROWS, RunReport, SWITCH_AT, VertexState, counted, fixpoint, sized
from tidegraph.plans.layout import DealtEdges
from tidegraph.runtime import Scratch


def _improve(edges: DealtEdges, start: DataFrame, rows: int, current: DataFrame) -> DataFrame:
    side = start.select(F.col("id").alias("src"), F.col("value").alias("label"))
    side = sized(side, rows) if 0 < rows <= BROADCAST_ROWS else side
    least = edges.meet(side).groupBy(F.col("dst").alias("id")).agg(F.min("label").alias("new"))
    return current.join(least, "id").where("new < value").select("id", F.col("new").alias("value"))


def connected_components(
    graph: PropertyGraph, direction: str = "symmetric", mode: str = "incremental", apply: str = "auto", switch_at: int = SWITCH_AT, full_rounds: int = 3, frontier: str = "exact", max_rounds: int = 10_000
) -> tuple[DataFrame, RunReport]:
    """``(id, component)``, each component named by its smallest id, and the run's report.

    ``direction``: 'symmetric' passes labels both ways in every round; 'alternate' along edges and against them in turn,
    with a copy of the edges for each; 'forward' along edges only, which gives the smallest id among a vertex's ancestors,
    not a component. The first ``full_rounds`` rounds of 'alternate' start from all vertices.

    ``frontier`` of 'alternate': 'exact' starts from what changed since its direction was last used and ends after two quiet
    rounds; 'literal' starts from the last round's changes only and ends after one, which loses changes that never pass
    along the other direction and can end early with wrong labels.
    """
    ids = graph.vertices.select("id", F.col("id").alias("value"))
    state = VertexState(ids, apply, switch_at, keep_deltas=direction == "alternate")
    pairs = graph.edges.select("src", "dst").where("src <> dst")
    back = pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    if direction in ("symmetric", "forward"):
        edges = DealtEdges(pairs.unionByName(back).distinct() if direction == "symmetric" else pairs)

        def step(changed, rows, current, k):
            return _improve(edges, current if mode == "full" else changed, 0 if mode == "full" else rows, current)

        report = fixpoint(state, state.base.df, step, max_rounds)
        edges.unpersist()
        return state.current().withColumnRenamed("value", "component"), report

    along = (DealtEdges(pairs), DealtEdges(back))
    report = RunReport()
    pending: list[list[tuple[Scratch, int]] | None] = [None, None]  # None: all vertices
    last: tuple[Scratch, int] | None = None
    deltas: list[Scratch] = []
    quiet = 0
    for k in range(1, max_rounds + 1):
        way, began = (k - 1) % 2, time.time()
        current = state.current()
        if k <= full_rounds or mode == "full" or (frontier == "exact" and pending[way] is None) or (frontier == "literal" and last is None):
            start, rows = current, 0
        elif frontier == "literal":
            start, rows = last[0].df, last[1]
        else:
            parts = pending[way]
            rows = sum(n for _, n in parts)
            if not parts:
                start, rows = current.limit(0), 0
            else:
                start = parts[0][0].df
                for x, _ in parts[1:]:
                    start = start.unionByName(x.df)
                start = start.groupBy("id").agg(F.min("value").alias("value"))
        delta, updates = counted(_improve(along[way], start, rows, current), "delta")
        applied = state.apply(delta, updates) if updates else "none"
        report.rounds.append({"round": k, "seconds": time.time() - began, "updates": updates, "applied": applied})
        pending[way] = []
        for other in (0, 1):
            if pending[other] is not None and updates:
                pending[other] = [*pending[other], (delta, updates)]
        last = (delta, updates)
        wanted = {id(x) for p in pending if p for x, _ in p} | {id(delta)}
        for x in deltas:
            if id(x) not in wanted:
                state.release(x)
        deltas = [*(x for x in deltas if id(x) in wanted or any(x is y for y, _ in state.overlay)), delta]
        quiet = 0 if updates else quiet + 1
        if quiet >= (1 if frontier == "literal" else 2):
            report.converged = True
            break
    for x in along:
        x.unpersist()
    return state.current().withColumnRenamed("value", "component"), report


def connected_components_star(graph: PropertyGraph) -> DataFrame:
    """``(id, component)`` by star contraction: few rounds whatever the diameter; ids must be longs."""
    found = star_components(graph.edges.select(F.col("src").alias("a"), F.col("dst").alias("b")))
    return graph.vertices.select("id").join(found, "id", "left").select("id", F.coalesce("component", "id").alias("component"))
