"""A small logical form of one superstep and the rewrites that make it a join and an aggregate.

The fixed plan of vertex-centric systems joins vertices, edges and messages, calls a function and writes new vertices and
new messages. The rules drop the stored messages, restrict the sources to those that changed, and leave out the join with
target vertices where nothing of it is read.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, functions as F

from tidegraph.graph import PropertyGraph

COMBINERS = {"min": F.min, "max": F.max, "sum": F.sum, "count": F.count}


@dataclass(frozen=True)
class VertexFunction:
    """A vertex function as an aggregate and a test: ``message(value, weight)``, how messages combine, and whether a new value is accepted."""

    message: Callable[[Column, Column], Column]
    combine: str = "min"
    accept: Callable[[Column, Column], Column] | None = None


def improves(old: Column, new: Column) -> Column:
    return old.isNull() | (new < old)


@dataclass(frozen=True)
class Step:
    """One superstep. ``stored_messages``: messages are a relation that is written and read again; ``frontier``: only changed
    vertices send; ``target_join``: targets are looked up among the vertices though only their id is used; ``reads_old``: the
    accept test reads the old value, so targets must be looked up."""

    function: VertexFunction
    stored_messages: bool = True
    pushed_compute: bool = False
    frontier: bool = False
    target_join: bool = True
    reads_old: bool = True
    join: str = "merge"


def push_compute(step: Step) -> Step:
    """Make the new messages from the new vertices and the edges, after the function has run."""
    return replace(step, pushed_compute=True)


def drop_messages(step: Step) -> Step:
    """Replace the stored messages by the join of vertices and edges that makes them."""
    return replace(step, stored_messages=False) if step.pushed_compute else step


def incremental(step: Step) -> Step:
    """Let only changed vertices send; right for combiners that keep the best of old and new."""
    return replace(step, frontier=True) if step.function.combine in ("min", "max") else step


def eliminate_join(step: Step, graph: PropertyGraph) -> Step:
    """Leave out the join with target vertices if every target is a vertex and no old value is read."""
    return replace(step, target_join=False) if graph.dst_in_vertices and not step.reads_old else step


def free_join(step: Step) -> Step:
    return replace(step, join="auto")


def rewrite(step: Step, graph: PropertyGraph) -> Step:
    """All rules, in order."""
    return free_join(eliminate_join(incremental(drop_messages(push_compute(step))), graph))


def superstep(step: Step, vertices: DataFrame, edges: DataFrame, senders: DataFrame, messages: DataFrame | None = None) -> DataFrame:
    """``(id, value)`` that the step accepts. ``edges(src, dst, w)``; ``senders(id, value)`` are all or the changed vertices."""
    hinted = lambda df: df if step.join == "auto" else df.hint(step.join)
    if step.stored_messages and messages is not None:
        made = messages
    else:
        made = edges.join(hinted(senders.withColumnRenamed("id", "src")), "src").select(F.col("dst").alias("id"), step.function.message(F.col("value"), F.col("w")).alias("payload"))
    combined = made.groupBy("id").agg(COMBINERS[step.function.combine]("payload").alias("new"))
    if not step.target_join:
        return combined.withColumnRenamed("new", "value")
    joined = vertices.join(hinted(combined), "id")
    accept = step.function.accept(F.col("value"), F.col("new")) if step.function.accept else F.lit(True)
    return joined.where(accept).select("id", F.col("new").alias("value"))


def gather_apply(graph: PropertyGraph, values: DataFrame, function: VertexFunction, weight: str | None = None) -> DataFrame:
    """One rewritten superstep from all vertices with a value."""
    w = F.col(weight) if weight else F.lit(1)
    step = rewrite(Step(function, reads_old=function.accept is not None), graph)
    return superstep(step, values, graph.edges.select("src", "dst", w.alias("w")), values.where("value is not null"))
