"""Shortest paths from one or more sources: frontier join edges, minimum by target, keep improvements."""

from __future__ import annotations

from contextlib import nullcontext

from pyspark.sql import DataFrame, functions as F, types as T

from tidegraph.graph import PropertyGraph, between
from tidegraph.plans.iterate import BROADCAST_ROWS, RunReport, SWITCH_AT, VertexState, fixpoint, sized
from tidegraph.plans.layout import DealtEdges, counted
from tidegraph.plans.physical import bloom_filters

#: Frontier ids up to which the edge scan gets a list to push down.
IN_LIST = 1_000
_HOPS, _EXACT = "bigint", "decimal(38,2)"


def narrowed(edges: DataFrame, frontier: DataFrame, rows: int, kind: str) -> DataFrame:
    """Edges that start in the frontier, by sideways information: a pushed list, a semi join, or left to the join itself."""
    if kind == "inlist" and rows <= IN_LIST:
        return edges.where(F.col("src").isin([r[0] for r in frontier.select("id").distinct().collect()]))  # IN_LIST ids at most
    if kind in ("semi", "inlist"):
        return edges.join(sized(frontier.select(F.col("id").alias("src")).distinct(), rows), "src", "left_semi")
    return edges


def sssp(
    graph: PropertyGraph, source, weight: str | None = None, mode: str = "incremental", apply: str = "auto", switch_at: int = SWITCH_AT, max_depth: int | None = None,
    sideways: str = "none", hint: str | None = None, with_parent: bool = False, cached: bool = True,
) -> tuple[DataFrame, RunReport]:
    """``(id, dist)`` of every vertex, null where it isn't reached, and the run's report.

    Hops are BIGINT; ``weight`` sums a column as exact decimals. ``mode``: 'incremental' joins only vertices that changed,
    'full' all reached ones. ``apply``: how updates are taken over (see VertexState). ``sideways``: how the edge scan is
    narrowed ('none', 'semi', 'inlist', 'bloom'). ``hint``: a join strategy. ``with_parent`` adds the neighbour a shortest path
    comes from, the smallest of ties. ``max_depth`` bounds the rounds. ``cached=False`` scans the edges as they lie in every
    round, which is right for bucketed copies and pushed filters. A source that is no vertex reaches nothing.
    """
    kind = _EXACT if weight else _HOPS
    step_cost = F.col(weight).cast("decimal(18,2)") if weight else F.lit(1)
    edges = graph.edges.select("src", "dst", step_cost.alias("w"))
    dealt = DealtEdges(edges, cached)
    zero = F.when(F.col("id") == F.lit(source), F.lit(0)).cast(kind)
    state = VertexState(graph.vertices.select("id", zero.alias("value")), apply, switch_at)
    frontier = state.base.df.where("value is not null")

    def step(changed: DataFrame, rows: int, current: DataFrame, k: int) -> DataFrame:
        start = current.where("value is not null") if mode == "full" else changed
        known = mode != "full" and 0 < rows <= BROADCAST_ROWS
        scan = narrowed(dealt.df, start, rows, sideways) if known else None
        side = start.select(F.col("id").alias("src"), F.col("value").alias("d"))
        side = side.hint(hint) if hint else sized(side, rows) if known and sideways != "bloom" else side
        least = dealt.meet(side, scan).groupBy(F.col("dst").alias("id")).agg(F.min((F.col("d") + F.col("w")).cast(kind)).alias("new"))
        return current.join(least, "id").where("value is null or new < value").select("id", F.col("new").alias("value"))

    filters = bloom_filters(graph.vertices.sparkSession) if sideways == "bloom" else nullcontext()
    with filters:
        report = fixpoint(state, frontier, step, max_depth or 10_000)
    result = state.current().select("id", F.col("value").alias("dist"))
    if with_parent:
        near = result.select(F.col("id").alias("src"), F.col("dist").alias("d"))
        came = dealt.meet(near).join(result.withColumnRenamed("id", "dst"), "dst").where("d + w = dist").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
        result = result.join(came, "id", "left").withColumn("parent", F.when(F.col("id") == F.lit(source), None).otherwise(F.col("parent")))
    dealt.unpersist()
    return result, report


def multi_source(graph: PropertyGraph, sources: list, max_depth: int) -> DataFrame:
    """``(source, id, dist)`` of the vertices within ``max_depth`` hops of each source; all sources in one job a round."""
    spark = graph.vertices.sparkSession
    kind = dict(graph.vertices.dtypes)["id"]
    start = spark.createDataFrame([(s,) for s in sources], T._parse_datatype_string(f"id {kind}"))
    reached = start.join(graph.vertices.select("id"), "id", "left_semi").select(F.col("id").alias("source"), "id", F.lit(0).cast("bigint").alias("dist"))
    edges = DealtEdges(graph.edges.select("src", "dst"))
    level, n = counted(reached, "level")
    levels = [level.df]
    for k in range(1, max_depth + 1):
        known = levels[0]
        for x in levels[1:]:
            known = known.unionByName(x)
        after = edges.meet(sized(level.df.select(F.col("id").alias("src"), "source"), n)).select("source", F.col("dst").alias("id")).distinct()
        fresh = after.join(known.select("source", "id"), ["source", "id"], "left_anti").withColumn("dist", F.lit(k).cast("bigint"))
        level, n = counted(fresh, "level")
        levels.append(level.df)
        if not n:
            break
    edges.unpersist()
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def bfs(graph: PropertyGraph, source) -> DataFrame:
    """``(id, level)`` of the vertices that can be reached."""
    return sssp(graph, source)[0].where("dist is not null").withColumnRenamed("dist", "level")


def khop(graph: PropertyGraph, source, hops: int, direction: str = "out") -> PropertyGraph:
    """The subgraph of the vertices within ``hops`` of ``source``; ``direction`` 'out', 'in' or 'both'."""
    walk = {"out": lambda: graph, "in": graph.reversed, "both": graph.symmetrised}[direction]()
    near, _ = sssp(walk, source, max_depth=hops)
    ids = near.where("dist is not null").select("id")
    vertices = graph.vertices.join(ids, "id", "left_semi")
    return PropertyGraph(vertices, between(graph.edges, ids), graph.directed, True)


def khop_recursive_sql(graph: PropertyGraph, source: int, hops: int) -> DataFrame:
    """``(id, dist)`` within ``hops``, as one recursive SQL statement.

    Each step walks on from the distinct vertices of the step before, whether or not they were met earlier, and Spark ends
    a recursion of over ``spark.sql.cteRecursionRowLimit`` rows with an error: for few hops on graphs of moderate size; others take ``sssp``.
    """
    edges = graph.edges.select("src", "dst").distinct()
    return graph.vertices.sparkSession.sql(
        """WITH RECURSIVE walk(id, dist) AS (
             SELECT CAST(:source AS BIGINT), 0
             UNION ALL SELECT DISTINCT e.dst, walk.dist + 1 FROM walk JOIN {edges} e ON e.src = walk.id WHERE walk.dist < :hops)
           SELECT id, CAST(min(dist) AS BIGINT) AS dist FROM walk GROUP BY id""",
        args={"source": source, "hops": hops},
        edges=edges,
    )


#: Edges of a group that is explored in one worker's memory.
GROUP_EDGES = 1_000_000


def sssp_local_rounds(graph: PropertyGraph, source, parts: int | None = None, local_rounds: int = 3, max_rounds: int = 200) -> tuple[DataFrame, int]:
    """Hop distances with ``local_rounds`` relaxations inside each group of edges before groups exchange; ``(result, global rounds)``.

    Groups are dealt by edge source and hold GROUP_EDGES edges on average; each relaxes its own edges in memory, so fewer
    global rounds are needed.
    """
    import pandas as pd

    from tidegraph.runtime import ship

    ship(graph.vertices.sparkSession)
    written, n = counted(graph.edges.select("src", "dst"), "edges")
    parts = parts or max(4, -(-n // GROUP_EDGES))
    edges = written.df.select(F.pmod(F.xxhash64("src"), F.lit(parts)).cast("int").alias("part"), "src", "dst")
    state = VertexState(graph.vertices.select("id", F.when(F.col("id") == F.lit(source), 0).cast("bigint").alias("value")), "replace")

    def relax(e: pd.DataFrame, v: pd.DataFrame) -> pd.DataFrame:
        best = dict(zip(v["id"], v["value"]))
        found: dict = {}
        by = e.groupby("src")["dst"].apply(list).to_dict() if len(e) else {}
        wave = [x for x in best if x in by]
        for _ in range(local_rounds):
            after = []
            for u in wave:
                for x in by.get(u, ()):
                    if best[u] + 1 < best.get(x, 1 << 60):
                        best[x] = found[x] = best[u] + 1
                        after.append(x)
            wave = after
        return pd.DataFrame({"id": list(found), "value": list(found.values())}, dtype="int64")

    frontier, k = state.base.df.where("value is not null"), 0
    for k in range(1, max_rounds + 1):
        dealt = frontier.select(F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int").alias("part"), "id", "value")
        own = edges.groupBy("part").cogroup(dealt.groupBy("part")).applyInPandas(relax, "id long, value long")
        least = own.groupBy("id").agg(F.min("value").alias("new"))
        delta, n = counted(state.current().join(least, "id").where("value is null or new < value").select("id", F.col("new").alias("value")), "delta")
        if not n:
            break
        state.apply(delta, n)
        if k > 1:
            state.release(before)
        frontier, before = delta.df, delta
    return state.current().select("id", F.col("value").alias("dist")), k
