"""The registered workloads of the graph engine, and their SQL twins."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from tidegraph import oracle_graphs as O
from tidegraph.baselines.engines import async_run, bsp_run, onehop_messages, row_layout, stitched, stitched_analysis
from tidegraph.functions import relational as R
from tidegraph.graph import PropertyGraph
from tidegraph.operators import blocks, labels as L, motifs as M
from tidegraph.operators.pagerank import pagerank
from tidegraph.operators.sssp import bfs, khop, khop_recursive_sql, multi_source, sssp, sssp_local_rounds
from tidegraph.plans import layout, physical
from tidegraph.plans.iterate import RunReport
from tidegraph.plans.logical import VertexFunction, gather_apply, improves
from tidegraph.runtime import materialize, scratch_root
from tidegraph.sources import derived as G
from tidegraph.vertexprog import udf
from tidegraph.vertexprog.api import Components, NeighbourOverlap, NeighbourTies, Ranking, ShortestPath
from tidegraph.vertexprog.cf import collaborative_filtering, rating_cells
from tidegraph.vertexprog.runners import run_program

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def _rounded(df: DataFrame, column: str = "rank") -> DataFrame:
    return df.select("id", F.round(column, 9).alias(column))


def _g1(spark, d) -> PropertyGraph:
    return G.handoff(spark, d).narrow().distinct()


def _least_source(graph: PropertyGraph):
    """The smallest id with an out-edge."""
    return graph.edges.agg(F.min("src")).first()[0]


_RANKS = "SELECT id, round(rank, 9) AS rank FROM r{k}"


# PageRank and its variants
@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)} {_RANKS.format(k=10)}")
def w_pagerank_10(spark, d):
    return _rounded(pagerank(_g1(spark, d)))


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10, 'literal')} {_RANKS.format(k=10)}")
def w_pagerank_literal(spark, d):
    return _rounded(pagerank(_g1(spark, d), sources="literal"))


@query(f"WITH {O.G3}, g3d AS (SELECT DISTINCT src, dst FROM g3), {O.pagerank('g3d', 'g3v', 10, 'literal')} {_RANKS.format(k=10)}")
def w_pagerank_literal_events(spark, d):
    return _rounded(pagerank(G.user_sequence(spark, d).narrow().distinct(), sources="literal"))


@query(f"WITH {O.G7}, {O.pagerank('g7', 'g7v', 10)} {_RANKS.format(k=10)}")
def w_pagerank_sparse(spark, d):
    return _rounded(pagerank(G.replies(spark, d)))


@query(f"WITH {O.G7}, {O.pagerank('g7', 'g7v', 10, 'redistribute')} {_RANKS.format(k=10)}")
def w_pagerank_redistribute(spark, d):
    return _rounded(pagerank(G.replies(spark, d), sources="redistribute"))


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 3)} {_RANKS.format(k=3)}")
def w_pagerank_3(spark, d):
    """Three rounds as a table function over united input."""
    g = _g1(spark, d)
    out, _ = run_program(g, Ranking(g.vertices.count(), 3), "union")
    return _rounded(out, "state").withColumnRenamed("state", "rank")


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 60)}, {O.first_settled(60, 1e-10)} SELECT id, round(rank, 9) AS rank FROM settled")
def w_pagerank_tolerance(spark, d):
    return _rounded(pagerank(_g1(spark, d), rounds=60, tol=1e-10))


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10, 'redistribute', start='(SELECT min(src) FROM g1d)')} {_RANKS.format(k=10)}")
def w_pagerank_personalised(spark, d):
    g = _g1(spark, d)
    return _rounded(pagerank(g, source_ids=[_least_source(g)], sources="redistribute"))


@query(f"WITH {O.G1}, g1v AS (SELECT c_custkey AS id FROM customer), {O.pagerank('g1', 'g1v', 10, weight='weight::DOUBLE')} {_RANKS.format(k=10)}")
def w_pagerank_weighted(spark, d):
    """Shares by order value over parallel edges."""
    return _rounded(pagerank(G.handoff(spark, d).narrow("weight"), weight="weight"))


@contextmanager
def _bucketed(spark, graph: PropertyGraph):
    """The graph over two bucketed and sorted copies of its edges and one of its vertices."""
    tables = layout.write_bucketed(graph, f"copy_{uuid.uuid4().hex[:8]}", int(spark.conf.get("spark.sql.shuffle.partitions")))
    try:
        yield PropertyGraph(spark.table(tables["id"]), spark.table(tables["src"]).select("src", "dst"), graph.directed, graph.dst_in_vertices)
    finally:
        for t in tables.values():
            spark.sql(f"DROP TABLE {t}")


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)} {_RANKS.format(k=10)}")
def w_pagerank_bucketed(spark, d):
    """Every round scans the copy that is bucketed by source; only sums by target move."""
    with _bucketed(spark, _g1(spark, d)) as g:
        return _rounded(materialize(pagerank(g, cached=False), "ranks").df)


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', '(SELECT min(src) FROM g2)')} SELECT v.id, d.dist FROM g2v v LEFT JOIN d USING (id)")
def w_sssp_bucketed(spark, d):
    with _bucketed(spark, G.co_purchase(spark, d)) as g:
        return materialize(sssp(g, _least_source(g), cached=False)[0], "distances").df


# Shortest paths
_G2_FROM = "(SELECT min(src) FROM g2)"


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT v.id, d.dist FROM g2v v LEFT JOIN d USING (id)")
def w_sssp_hops(spark, d):
    g = G.co_purchase(spark, d)
    return sssp(g, _least_source(g))[0]


@query(f"WITH RECURSIVE {O.G1D}, {O.levels('g1d', '0::BIGINT')} SELECT v.id, d.dist FROM g1v v LEFT JOIN d USING (id)")
def w_sssp_hops_directed(spark, d):
    return sssp(_g1(spark, d), 0)[0]


_WEIGHTED = f"""WITH RECURSIVE {O.G1}, g1w AS (SELECT src, dst, min(weight::DECIMAL(18,2)) AS w FROM g1 GROUP BY ALL),
d(id, dist) USING KEY (id) AS (SELECT 0::BIGINT AS id, 0::DECIMAL(38,2) AS dist UNION
  SELECT e.dst, min((x.dist + e.w)::DECIMAL(38,2)) FROM d x JOIN g1w e ON e.src = x.id LEFT JOIN recurring.d p ON p.id = e.dst WHERE p.dist IS NULL OR x.dist + e.w < p.dist GROUP BY e.dst)
SELECT c_custkey AS id, round(d.dist::DOUBLE, 2) AS dist FROM customer LEFT JOIN d ON d.id = c_custkey"""


@query(_WEIGHTED)
def w_sssp_weighted(spark, d):
    g = G.handoff(spark, d).narrow("weight").distinct("min_weight")
    return sssp(g, 0, "weight")[0].select("id", F.round(F.col("dist").cast("double"), 2).alias("dist"))


@query(f"WITH RECURSIVE {O.G1D}, {O.levels('g1d', '0::BIGINT')}, p AS (SELECT e.dst AS id, min(e.src) AS parent FROM g1d e JOIN d a ON a.id = e.src JOIN d b ON b.id = e.dst WHERE a.dist + 1 = b.dist GROUP BY e.dst) SELECT v.id, d.dist, p.parent FROM g1v v LEFT JOIN d USING (id) LEFT JOIN p USING (id)")
def w_sssp_parents(spark, d):
    return sssp(_g1(spark, d), 0, with_parent=True)[0]


@query(f"WITH RECURSIVE {O.G1D}, {O.levels('g1d', '0::BIGINT')} SELECT id, dist AS level FROM d")
def w_bfs(spark, d):
    return bfs(_g1(spark, d), 0)


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT v.id, d.dist FROM g2v v LEFT JOIN d USING (id)")
def w_sssp_grouped_exploration(spark, d):
    g = G.co_purchase(spark, d)
    return sssp_local_rounds(g, _least_source(g))[0]


@query(f"WITH RECURSIVE {O.G3}, s AS (SELECT unnest([0, 1, 2]::BIGINT[]) AS source), w(source, id, dist) AS (SELECT source, source, 0::BIGINT FROM s WHERE source IN (SELECT id FROM g3v) UNION SELECT w.source, e.dst, w.dist + 1 FROM w JOIN g3 e ON e.src = w.id WHERE w.dist < 2) SELECT source, id, min(dist) AS dist FROM w GROUP BY ALL")
def w_khop_sssp(spark, d):
    return multi_source(G.user_sequence(spark, d).narrow().distinct(), [0, 1, 2], 2)


@query(f"WITH RECURSIVE {O.G1D}, {O.bfs('g1d', '(SELECT min(src) FROM g1d)', depth=3)} SELECT e.src, e.dst FROM g1d e JOIN d a ON a.id = e.src JOIN d b ON b.id = e.dst")
def w_khop_subgraph(spark, d):
    g = _g1(spark, d)
    return khop(g, _least_source(g), 3).edges.select("src", "dst")


@query(f"WITH RECURSIVE {O.G1D}, {O.bfs('g1d', '(SELECT min(src) FROM g1d)', depth=4)} SELECT id, dist FROM d")
def w_khop_recursive_sql(spark, d):
    g = _g1(spark, d)
    return khop_recursive_sql(g, _least_source(g), 4)


# Connected components
_CC_G1 = f"WITH RECURSIVE {O.G1D}, {O.both_ways('g1d', 'b')}, {O.labels('b', 'g1v')} SELECT id, component FROM c"
_CC_G2 = f"WITH RECURSIVE {O.G2}, {O.labels('g2', 'g2v')} SELECT id, component FROM c"


@query(_CC_G1)
def w_cc(spark, d):
    return L.connected_components(_g1(spark, d))[0]


@query(_CC_G1)
def w_cc_star(spark, d):
    return L.connected_components_star(_g1(spark, d))


@query(_CC_G2)
def w_cc_alternate(spark, d):
    return L.connected_components(G.co_purchase(spark, d), "alternate")[0]


@query("SELECT doc_id AS id, CASE WHEN text IS NULL THEN doc_id ELSE min(doc_id) OVER (PARTITION BY text) END AS component FROM documents")
def w_cc_duplicates(spark, d):
    return L.connected_components_star(G.duplicates(spark, d))


@query("SELECT conv_id * 1000 + turn AS id, conv_id * 1000 + min(turn) OVER (PARTITION BY conv_id) AS component FROM conversations")
def w_cc_replies(spark, d):
    return L.connected_components(G.replies(spark, d))[0]


@query(f"WITH RECURSIVE {O.G1D}, {O.labels('g1d', 'g1v')} SELECT id, component FROM c")
def w_cc_forward(spark, d):
    return L.connected_components(_g1(spark, d), "forward")[0]


@query()
def w_cc_frontier_ablation(spark, d):
    """Alternating propagation with the exact and the literal frontier on a dense directed graph, against components."""
    g = _g1(spark, d)
    truth = L.connected_components_star(g)
    out = None
    for kind in ("exact", "literal"):
        found, report = L.connected_components(g, "alternate", frontier=kind, full_rounds=0)
        wrong = found.withColumnRenamed("component", "c").join(truth, "id").agg(F.count_if(F.col("c") != F.col("component")).alias("wrong"))
        row = wrong.select(F.lit(kind).alias("frontier"), F.lit(len(report.rounds)).cast("long").alias("rounds"), "wrong")
        out = row if out is None else out.unionByName(row)
    return out


# Measures by round, phase and resource
_ROUNDS = "algorithm string, round long, updates long, seconds double, applied string"


def _report_rows(spark, algorithm: str, report) -> DataFrame:
    return spark.createDataFrame([(algorithm, r["round"], r["updates"], float(r["seconds"]), r["applied"]) for r in report.rounds], _ROUNDS)


@query(f"WITH RECURSIVE {O.G1D}, {O.levels('g1d', '0::BIGINT')}, n AS (SELECT dist AS round, count(*) AS updates FROM d WHERE dist > 0 GROUP BY dist) SELECT round, updates FROM n UNION ALL SELECT max(round) + 1, 0 FROM n")
def w_per_round(spark, d):
    """Updates by round of incremental shortest paths: the sizes of the levels."""
    _, report = sssp(_g1(spark, d), 0)
    return _report_rows(spark, "sssp", report).select("round", "updates")


@query(f"WITH RECURSIVE {O.G1D}, {O.levels('g1d', '0::BIGINT')}, o AS (SELECT src AS id, count(*) AS o FROM g1d GROUP BY src), n AS (SELECT d.dist, sum(coalesce(o, 0))::BIGINT AS n FROM d LEFT JOIN o USING (id) GROUP BY d.dist) SELECT dist + 1 AS round, n AS incremental, (sum(n) OVER (ORDER BY dist))::BIGINT AS full_join, (SELECT count(*) FROM g1d) AS superstep FROM n")
def w_join_rows(spark, d):
    """Rows that the join with edges gives by round: from changed vertices, from all reached ones, and from all vertices as the fixed plan scans them."""
    g = _g1(spark, d)
    dist = materialize(sssp(g, 0)[0].where("dist is not null"), "reached").df
    out = g.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("o"))
    level = dist.join(out, "id", "left").groupBy("dist").agg(F.sum(F.coalesce("o", F.lit(0))).alias("n"))  # a row for each level
    every = F.broadcast(g.edges.agg(F.count(F.lit(1)).alias("superstep")))  # one row
    below = level.withColumnRenamed("n", "m").withColumnRenamed("dist", "k")
    summed = level.join(below, F.col("k") <= F.col("dist")).groupBy("dist", "n").agg(F.sum("m").alias("full_join"))
    return summed.crossJoin(every).select((F.col("dist") + 1).alias("round"), F.col("n").alias("incremental"), "full_join", "superstep")


@query()
def w_per_round_seconds(spark, d):
    """Seconds by round of PageRank, shortest paths and components, as SQL plans and as superstep runs."""
    g = _g1(spark, d)
    ranks = RunReport()
    pagerank(g, report=ranks)
    reports = {"pagerank": ranks, "sssp": sssp(g, 0)[1], "components": L.connected_components(g)[1], "components_alternating": L.connected_components(g, "alternate")[1]}
    reports |= {"superstep_pagerank": bsp_run(g, kind="pagerank")[1], "superstep_sssp": bsp_run(g, 0)[1], "superstep_components": bsp_run(g.symmetrised(), kind="components")[1]}
    rows = [(name, r["round"], r["updates"], float(r["seconds"]), r["applied"]) for name, report in reports.items() for r in report.rounds]
    return spark.createDataFrame(rows, _ROUNDS)


@query()
def w_cost_breakdown(spark, d):
    """Seconds by phase of the superstep engine, the shared-memory engine and the SQL plan, for the three analyses."""
    g, rows = _g1(spark, d), []
    both = g.symmetrised()
    for kind in ("pagerank", "sssp", "components"):
        graph = both if kind == "components" else g
        for engine, run in (("superstep", bsp_run), ("shared_memory", async_run)):
            rows += [(kind, engine, k, float(v)) for k, v in run(graph, 0, kind)[1].phases.items()]
        t = time.time()
        {"pagerank": lambda: pagerank(g), "sssp": lambda: sssp(g, 0), "components": lambda: L.connected_components(g)}[kind]()
        rows.append((kind, "sql", "analysis", time.time() - t))
    return spark.createDataFrame(rows, "analysis string, engine string, phase string, seconds double")


@query()
def w_io(spark, d):
    """Bytes read, written, shuffled and spilled by round of PageRank, ten rounds each, as SQL plan and as superstep run."""
    from tidegraph.functions.metrics import round_figures

    g, ranks = _g1(spark, d), RunReport()
    pagerank(g, report=ranks)
    return round_figures(spark, "sql", ranks).unionByName(round_figures(spark, "superstep", bsp_run(g, kind="pagerank")[1]))


@query()
def w_memory(spark, d):
    """Peak memory of the driver's process tree and of a task over PageRank runs of ten rounds, by engine."""
    from tidegraph.functions.metrics import with_memory

    g = _g1(spark, d)
    runs = {"sql": lambda: pagerank(g), "superstep": lambda: bsp_run(g, kind="pagerank"), "shared_memory": lambda: async_run(g, kind="pagerank")}
    return with_memory(spark, runs)


@query()
def w_cold_runs(spark, d):
    """Three runs each after dropping what is cached, and their mean."""
    from tidegraph.functions.metrics import measured

    g, out = _g1(spark, d), None
    for name, run in (("pagerank", lambda: pagerank(g)), ("sssp", lambda: sssp(g, 0)), ("superstep_pagerank", lambda: bsp_run(g, kind="pagerank"))):
        rows = measured(spark, name, run, repeats=3).select("run", "seconds")
        out = rows if out is None else out.unionByName(rows)
    name = F.substring_index("run", "#", 1)
    return out.withColumn("mean_seconds", F.avg("seconds").over(W.partitionBy(name)))


@query()
def w_udf_breakdown(spark, d):
    """Seconds by phase of PageRank, ten rounds: table functions with rounds on disk, resident ones, the array form, and the SQL plan."""
    g = _g1(spark, d)
    n = g.vertices.count()
    rows = []
    for kind in ("union", "join", "resident", "barrier"):
        _, report = run_program(g, Ranking(n, 10), kind)
        rows += [(kind, k, float(v)) for k, v in report.phases.items()]
    t = time.time()
    pagerank(g)
    return spark.createDataFrame([*rows, ("sql", "analysis", time.time() - t)], "input string, phase string, seconds double")


@query()
def w_prepare(spark, d):
    """Seconds and bytes of text edge lists and of the two bucketed copies, by codec."""
    rows = []
    for name, g in (("handoff", G.handoff(spark, d).narrow()), ("co_purchase", G.co_purchase(spark, d))):
        folder = f"{scratch_root(spark)}/prepare-{time.time_ns()}"
        t = time.time()
        g.edges.write.csv(f"{folder}/text", sep="\t")
        rows.append((name, "text", time.time() - t, layout.stored_bytes(spark, f"{folder}/text")))
        for codec in ("zstd", "snappy", "none"):
            t = time.time()
            tables = layout.write_bucketed(g, f"prepared_{uuid.uuid4().hex[:8]}", 8, codec=codec)
            took = time.time() - t
            rows.append((name, f"bucketed_{codec}", took, sum(layout.table_bytes(spark, tables[end]) for end in ("src", "dst"))))
            for x in tables.values():
                spark.sql(f"DROP TABLE {x}")
    return spark.createDataFrame(rows, "graph string, layout string, seconds double, bytes long")


def _datasets(spark, d) -> dict[str, PropertyGraph]:
    return {"replies": G.replies(spark, d), "handoff": _g1(spark, d), "user_sequence": G.user_sequence(spark, d).narrow().distinct(), "trade": G.trade(spark, d), "co_purchase": G.co_purchase(spark, d)}


@query(f"WITH {O.G7}, {O.G1D}, {O.G3}, {O.G4}, {O.G2} SELECT 'replies' AS graph, (SELECT count(*) FROM g7v) AS vertices, (SELECT count(*) FROM g7) AS edges UNION ALL SELECT 'handoff', (SELECT count(*) FROM g1v), (SELECT count(*) FROM g1d) UNION ALL SELECT 'user_sequence', (SELECT count(*) FROM g3v), (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM g3)) UNION ALL SELECT 'trade', (SELECT count(DISTINCT src) + count(DISTINCT dst) FROM g4), (SELECT count(*) FROM g4) UNION ALL SELECT 'co_purchase', (SELECT count(*) FROM g2v), (SELECT count(*) FROM g2)")
def w_datasets(spark, d):
    """Vertices and edges of the graphs of the scale series."""
    rows = [(name, g.vertices.count(), g.edges.count()) for name, g in _datasets(spark, d).items()]
    return spark.createDataFrame(rows, "graph string, vertices long, edges long")


@query()
def w_scale_series(spark, d):
    """Seconds of PageRank (ten rounds), shortest paths and components by SQL plan over directed graphs of growing size."""
    rows = []
    for name, derived in _datasets(spark, d).items():
        # Derived once: otherwise every analysis would derive the graph again, and its seconds would be mostly that.
        kept_v, (kept_e, edges) = materialize(derived.vertices.select("id"), "series"), layout.counted(derived.edges.select("src", "dst"), "series")
        g = replace(derived, vertices=kept_v.df, edges=kept_e.df)
        for what, run in (("pagerank", lambda: pagerank(g).count()), ("sssp", lambda: sssp(g, _least_source(g))), ("components", lambda: L.connected_components_star(g).count())):
            t = time.time()
            run()
            rows.append((name, edges, what, time.time() - t))
        kept_v.drop()
        kept_e.drop()
    return spark.createDataFrame(rows, "graph string, edges long, analysis string, seconds double")


# Vertex programs and baselines give what the SQL plans give
_DIST2 = f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT v.id, d.dist::DOUBLE AS dist FROM g2v v LEFT JOIN d USING (id)"


def _program_sssp(kind: str):
    def run(spark, d):
        g = G.co_purchase(spark, d)
        return run_program(g, ShortestPath(_least_source(g)), kind)[0].withColumnRenamed("state", "dist")

    return run


for _kind, _name in (("union", "w_program_sssp_union"), ("join", "w_program_sssp_join"), ("resident", "w_resident_sssp"), ("barrier", "w_inmemory_sssp")):
    query(_DIST2, _name)(_program_sssp(_kind))


for _kind, _name in (("barrier", "w_inmemory_pagerank"), ("resident", "w_resident_pagerank")):

    @query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)} {_RANKS.format(k=10)}", _name)
    def _program_ranks(spark, d, kind=_kind):
        g = _g1(spark, d)
        return _rounded(run_program(g, Ranking(g.vertices.count(), 10), kind)[0], "state").withColumnRenamed("state", "rank")


for _kind, _name in (("barrier", "w_inmemory_cc"), ("resident", "w_resident_cc")):

    @query(f"WITH RECURSIVE {O.G2}, {O.labels('g2', 'g2v')} SELECT id, component::DOUBLE AS component FROM c", _name)
    def _program_labels(spark, d, kind=_kind):
        return run_program(G.co_purchase(spark, d), Components(), kind)[0].withColumnRenamed("state", "component")


_SYMMETRIC = f"WITH {O.G1D}, {O.both_ways('g1d', 'b')}"


@query(f"{_SYMMETRIC} {O.OVERLAP.format(e='b', t=1)}")
def w_program_overlap(spark, d):
    """Strong overlap as a vertex program of two supersteps."""
    out, _ = run_program(_g1(spark, d).symmetrised(), NeighbourOverlap(1), "union")
    return out.select(F.col("id").alias("n2"), F.explode("state").alias("x")).select(F.get("x", F.lit(0)).alias("n1"), "n2", F.get("x", F.lit(1)).alias("common"))


@query(f"{_SYMMETRIC} {O.TIES.format(e='b', t=100, h=2)}")
def w_program_ties(spark, d):
    """Weak ties as a vertex program of three supersteps."""
    out, _ = run_program(_g1(spark, d).symmetrised(), NeighbourTies(), "union")
    return out.where("state > 100").select("id", F.col("state").alias("pairs"))


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT v.id, d.dist AS value FROM g2v v LEFT JOIN d USING (id)")
def w_superstep_sssp(spark, d):
    g = G.co_purchase(spark, d)
    return bsp_run(g, _least_source(g))[0]


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)} SELECT id, round(rank, 9) AS value FROM r10")
def w_async_pagerank(spark, d):
    return async_run(_g1(spark, d), kind="pagerank")[0].select("id", F.round("value", 9).alias("value"))


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)} SELECT id, round(rank, 9) AS value FROM r10")
def w_superstep_pagerank(spark, d):
    return bsp_run(_g1(spark, d), kind="pagerank", rounds=10)[0].select("id", F.round("value", 9).alias("value"))


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT v.id, d.dist AS value FROM g2v v LEFT JOIN d USING (id)")
def w_async_sssp(spark, d):
    g = G.co_purchase(spark, d)
    return async_run(g, _least_source(g))[0]


@query(f"WITH RECURSIVE {O.G2}, {O.labels('g2', 'g2v')} SELECT id, component AS value FROM c")
def w_async_cc(spark, d):
    return async_run(G.co_purchase(spark, d), kind="components")[0]


# Graph and relational steps together
_W9 = "c_mktsegment in ('BUILDING', 'MACHINERY', 'HOUSEHOLD')", "etype in ('1-URGENT', '2-HIGH')"


def _w9(spark, d) -> PropertyGraph:
    return G.handoff(spark, d).subgraph(*_W9).narrow()


@query(f"WITH {O.W9}, {O.pagerank('w9', 'w9v', 10)} {_RANKS.format(k=10)}")
def w_subgraph_pagerank(spark, d):
    return _rounded(pagerank(_w9(spark, d)))


@query(f"WITH RECURSIVE {O.W9}, {O.levels('w9', '(SELECT min(src) FROM w9)')} SELECT v.id, d.dist FROM w9v v LEFT JOIN d USING (id)")
def w_subgraph_sssp(spark, d):
    g = _w9(spark, d)
    return sssp(g, _least_source(g))[0]


_HIST = """h AS (SELECT min(rank) AS a, max(rank) AS b FROM t), k AS (SELECT least(floor((rank - a) / (b - a) * 20)::INT, 19) AS bucket, count(*) AS n FROM t, h GROUP BY 1)
SELECT i::INT AS bucket, round(a + (b - a) * i / 20, 9) AS lo, round(a + (b - a) * (i + 1) / 20, 9) AS hi, coalesce(n, 0) AS n FROM range(20) r(i), h LEFT JOIN k ON k.bucket = i"""


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)}, t AS (SELECT round(rank, 9) AS rank FROM r10), {_HIST}")
def w_hist_pagerank(spark, d):
    return R.histogram(w_pagerank_10(spark, d), "rank", 20).select("bucket", F.round("lo", 9).alias("lo"), F.round("hi", 9).alias("hi"), "n")


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT dist, count(*) AS n FROM d GROUP BY dist")
def w_hist_distance(spark, d):
    return w_sssp_hops(spark, d).where("dist is not null").groupBy("dist").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH RECURSIVE {O.G1D}, {O.pagerank('g1d', 'g1v', 10)}, {O.levels('g1d', '0::BIGINT')} SELECT r.id, d.dist, round(r.rank, 9) AS rank FROM r10 r LEFT JOIN d USING (id) WHERE d.dist <= 2 OR r.rank > 2.0 / (SELECT count(*) FROM g1v)")
def w_near_or_important(spark, d):
    g = _g1(spark, d)
    n = g.vertices.count()
    return R.near_or_important(pagerank(g), sssp(g, 0)[0], 2, 2.0 / n).select("id", "dist", F.round("rank", 9).alias("rank"))


@query(f"WITH {O.G1D}, {O.pagerank('g1d', 'g1v', 10)} SELECT r.id, round(rank, 9) AS rank, c.c_name, c.c_mktsegment FROM r10 r JOIN customer c ON c.c_custkey = r.id WHERE rank > 2.0 / (SELECT count(*) FROM g1v)")
def w_rehydrate(spark, d):
    g = G.handoff(spark, d)
    ranks = pagerank(g.narrow().distinct())
    return R.rehydrate(ranks.where(F.col("rank") > 2.0 / g.vertices.count()), g.vertices, "c_name", "c_mktsegment").select("id", F.round("rank", 9).alias("rank"), "c_name", "c_mktsegment")


@query(f"WITH {O.G3} SELECT src, dst, count(*) AS n, round(sum(weight::DECIMAL(18,2))::DOUBLE, 2) AS total FROM g3 WHERE etype = 'purchase' AND created >= (SELECT max(ts) FROM events) - INTERVAL 7 DAYS GROUP BY ALL")
def w_time_filtered(spark, d):
    g = G.user_sequence(spark, d)
    last = G.table(spark, d, "events").agg(F.max("ts").alias("last"))
    recent = g.edges.where("etype = 'purchase'").crossJoin(F.broadcast(last)).where("created >= last - interval 7 days")
    return recent.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("weight").cast("double"), 2).alias("total"))


@query(f"WITH RECURSIVE {O.G1D}, {O.both_ways('g1d', 'b')}, {O.labels('b', 'g1v')} SELECT r_name, n_name, count(DISTINCT component) AS components, count(*) AS members FROM c JOIN customer ON c_custkey = id JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
def w_post_aggregate(spark, d):
    found = L.connected_components(_g1(spark, d))[0]
    places = G.table(spark, d, "customer").join(F.broadcast(G.table(spark, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(G.table(spark, d, "region")), F.col("r_regionkey") == F.col("n_regionkey"))  # 25 and 5 rows
    return found.join(places, F.col("id") == F.col("c_custkey")).rollup("r_name", "n_name").agg(F.count_distinct("component").alias("components"), F.count(F.lit(1)).alias("members"))


@query(f"WITH {O.G1} SELECT count(*) FILTER (WHERE etype = '1-URGENT') AS urgent, count(*) FILTER (WHERE weight > 100000) AS dear, count(*) FILTER (WHERE src < dst) AS upward FROM g1")
def w_profile(spark, d):
    return R.profile(G.handoff(spark, d).edges, urgent="etype = '1-URGENT'", dear="weight > 100000", upward="src < dst")


def _meta_columns() -> list[str]:
    return [n for n, *_ in R.attribute_plan()]


_META_ROUNDED = ", ".join(f"round({n}, 3) AS {n}" if n.startswith("attr_f") else n for n in _meta_columns())


@query(f"SELECT id, {_META_ROUNDED} FROM ({R.metadata_sql('(SELECT c_custkey AS id FROM customer)')})")
def w_metadata(spark, d):
    made = R.with_metadata(G.handoff(spark, d).vertices.select("id"))
    return made.select("id", *[F.round(n, 3).alias(n) if n.startswith("attr_f") else F.col(n) for n in _meta_columns()])


@query(f"WITH {O.W9} SELECT count(*) AS edges, count(DISTINCT src) AS sources FROM w9")
def w_row_vs_column(spark, d):
    """The selection over row-oriented copies of the handoff graph with its wide vertices."""
    g = G.handoff(spark, d)
    g = PropertyGraph(R.with_metadata(g.vertices), g.edges, True, True)
    return row_layout(g).subgraph(*_W9).edges.agg(F.count(F.lit(1)).alias("edges"), F.count_distinct("src").alias("sources"))


def _wide_handoff(spark, d) -> PropertyGraph:
    """The hand-off graph with all generated attributes on its vertices."""
    g = G.handoff(spark, d)
    return PropertyGraph(R.with_metadata(g.vertices), g.edges, True, True)


def _stitched(spark, d, kind: str) -> DataFrame:
    return stitched_analysis(row_layout(_wide_handoff(spark, d)), *_W9, kind)[0]


@query(f"WITH {O.W9}, {O.pagerank('w9', 'w9v', 10)} {_RANKS.format(k=10)}")
def w_stitched_pagerank(spark, d):
    """Selection by an input format over text rows, then the superstep engine, then text."""
    return _stitched(spark, d, "pagerank").select("id", F.round("value", 9).alias("rank"))


@query(f"WITH RECURSIVE {O.W9}, {O.levels('w9', '(SELECT min(src) FROM w9)')} SELECT v.id, d.dist FROM w9v v LEFT JOIN d USING (id)")
def w_stitched_sssp(spark, d):
    return _stitched(spark, d, "sssp").select("id", F.col("value").alias("dist"))


@query(ORACLES["w_hist_pagerank"])
def w_stitched_histogram(spark, d):
    """The superstep engine's ranks as text, and the histogram as a job of its own over them."""
    ranks = bsp_run(_g1(spark, d), kind="pagerank")[0].select("id", F.round("value", 9).alias("rank"))
    bins = [lambda r: R.histogram(r, "rank", 20).select("bucket", F.round("lo", 9).alias("lo"), F.round("hi", 9).alias("hi"), "n")]
    return stitched(bins, ranks)[0]


@query(ORACLES["w_near_or_important"])
def w_stitched_join(spark, d):
    """Two superstep runs, each stored as text, and a job that joins them."""
    g = _g1(spark, d)
    n = g.vertices.count()
    ranks, _ = stitched([], bsp_run(g, kind="pagerank")[0].withColumnRenamed("value", "rank"))
    hops, _ = stitched([], bsp_run(g, 0)[0].withColumnRenamed("value", "dist"))
    return R.near_or_important(ranks, hops, 2, 2.0 / n).select("id", "dist", F.round("rank", 9).alias("rank"))


@query()
def w_mixed_costs(spark, d):
    """Seconds of selection and analysis, histogram and join: the relational plan over columns against the stitched jobs over rows."""
    wide = _wide_handoff(spark, d)
    columns = PropertyGraph(materialize(wide.vertices, "wide").df, materialize(wide.edges, "wide").df, True, True)
    rows, out = row_layout(columns), []

    def relational(kind):
        g = columns.subgraph(*_W9).narrow()
        return pagerank(g) if kind == "pagerank" else sssp(g, _least_source(g))[0]

    def timed(analysis, engine, run):
        t = time.time()
        run()
        out.append((analysis, engine, time.time() - t))

    for kind in ("pagerank", "sssp"):
        timed(f"selection_{kind}", "sql", lambda: relational(kind).count())
        timed(f"selection_{kind}", "stitched", lambda: stitched_analysis(rows, *_W9, kind))
    timed("histogram", "sql", lambda: w_hist_pagerank(spark, d).count())
    timed("histogram", "stitched", lambda: w_stitched_histogram(spark, d).count())
    timed("join", "sql", lambda: w_near_or_important(spark, d).count())
    timed("join", "stitched", lambda: w_stitched_join(spark, d).count())
    return spark.createDataFrame(out, "analysis string, engine string, seconds double")


# One-hop analyses
@query(f"WITH {O.G2} {O.OVERLAP.format(e='g2', t=12)}")
def w_strong_overlap(spark, d):
    return M.strong_overlap(G.co_purchase(spark, d), 12)


@query(f"WITH {O.G5} {O.OVERLAP.format(e='g5', t=3)}")
def w_overlap_pages(spark, d):
    return M.strong_overlap(G.page_links(spark, d), 3)


_OV = O.PAIRS.format(e="g2") + ", s AS (SELECT src, count(*) AS d FROM g2 GROUP BY src), q AS (SELECT pairs.*, x.d AS d1, y.d AS d2 FROM pairs JOIN s x ON x.src = n1 JOIN s y ON y.src = n2)"
for _m, _f, _t in (("jaccard", "common / (d1 + d2 - common)", 0.06), ("cosine", "common / sqrt(d1 * d2)", 0.11), ("min", "common / least(d1, d2)", 0.12)):

    @query(f"WITH {O.G2}, {_OV} SELECT n1, n2, common, round({_f}, 9) AS value FROM q WHERE {_f} > {_t}", f"w_overlap_{_m}")
    def _overlap(spark, d, m=_m, t=_t):
        return M.strong_overlap(G.co_purchase(spark, d), t, measure=m).select("n1", "n2", "common", F.round("value", 9).alias("value"))


@query(f"WITH {O.G2}, {O.PAIRS.format(e='g2')}, w AS (SELECT n1, unnest(near[i + 1:]) AS n2, 1 / ln(len(near) + 1.0) AS w FROM firsts) SELECT n1, n2, count(*) AS common, round(sum(w), 6) AS value FROM w GROUP BY n1, n2 HAVING sum(w) > 2.6")
def w_overlap_adamic(spark, d):
    return M.strong_overlap(G.co_purchase(spark, d), 2.6, measure="adamic").select("n1", "n2", "common", F.round("value", 6).alias("value"))


for _form in ("anti", "left", "identity"):

    @query(f"WITH {O.G2} {O.TIES.format(e='g2', t=6000, h=2)}", "w_weak_ties" + ("" if _form == "anti" else f"_{_form}"))
    def _ties(spark, d, form=_form):
        return M.weak_ties(G.co_purchase(spark, d), 6000, form=form)


@query(f"WITH {O.G1D} {O.TIES.format(e='g1d', t=60, h=1)}")
def w_weak_ties_directed(spark, d):
    """Pairs that no edge leads back from the end to the start of, on a directed graph."""
    return M.weak_ties(_g1(spark, d), 60)


@query(f"WITH {O.G1D} {O.TIES.format(e='g1d', t=60, h=1)}")
def w_weak_ties_directed_left(spark, d):
    return M.weak_ties(_g1(spark, d), 60, form="left")


@query(f"WITH {O.G4} {O.OVERLAP.format(e='g4', t=18)}")
def w_overlap_trade(spark, d):
    """Customers that share many suppliers, on the dense bipartite graph."""
    return M.strong_overlap(G.trade(spark, d), 18)


@query(f"WITH {O.G2} SELECT count(*) AS triangles FROM ({O.TRIANGLES.format(e='g2')})")
def w_triangles(spark, d):
    return M.triangle_count(G.co_purchase(spark, d))


@query(f"WITH {O.G2} SELECT count(*) AS triangles FROM ({O.TRIANGLES.format(e='g2')})")
def w_triangles_by_id(spark, d):
    return M.triangle_count(G.co_purchase(spark, d), orient="id")


@query(f"WITH {O.G2}, t AS ({O.TRIANGLES.format(e='g2')}), n AS (SELECT id, count(*) AS n FROM (SELECT unnest([a, b, c]) AS id FROM t) GROUP BY id) SELECT v.id, coalesce(n.n, 0) AS triangles FROM g2v v LEFT JOIN n USING (id)")
def w_triangles_per_vertex(spark, d):
    return M.triangle_count(G.co_purchase(spark, d), True)


@query(f"WITH {O.G2}, t AS ({O.TRIANGLES.format(e='g2')}), n AS (SELECT id, count(*) AS n FROM (SELECT unnest([a, b, c]) AS id FROM t) GROUP BY id), d AS (SELECT src AS id, count(*) AS d FROM g2 GROUP BY src) SELECT v.id, round(CASE WHEN d.d > 1 THEN 2.0 * coalesce(n.n, 0) / (d.d * (d.d - 1)) ELSE 0 END::DOUBLE, 9) AS coefficient FROM g2v v LEFT JOIN n USING (id) LEFT JOIN d USING (id)")
def w_clustering(spark, d):
    return _rounded(M.clustering(G.co_purchase(spark, d)), "coefficient")


@query(f"WITH {O.G1}, o AS (SELECT src AS id, count(*) AS n FROM g1 GROUP BY src), i AS (SELECT dst AS id, count(*) AS n FROM g1 GROUP BY dst) SELECT c_custkey AS id, coalesce(o.n, 0) AS out_degree, coalesce(i.n, 0) AS in_degree, coalesce(o.n, 0) + coalesce(i.n, 0) AS degree FROM customer LEFT JOIN o ON o.id = c_custkey LEFT JOIN i ON i.id = c_custkey")
def w_degrees(spark, d):
    return M.degrees(G.handoff(spark, d))


@query()
def w_triangle_sample(spark, d):
    return M.estimated_triangles(G.co_purchase(spark, d), 0.5)


@query(f"WITH {O.G2} {O.OVERLAP.format(e='g2', t=12)}")
def w_onehop_overlap(spark, d):
    return onehop_messages(G.co_purchase(spark, d), "overlap", 12, "smaller_ids")[0]


@query(f"WITH {O.G2} {O.TIES.format(e='g2', t=6000, h=2)}")
def w_onehop_ties(spark, d):
    return onehop_messages(G.co_purchase(spark, d), "ties", 6000)[0]


@query(f"WITH {O.G2} SELECT count(*) AS triangles FROM ({O.TRIANGLES.format(e='g2')})")
def w_onehop_triangles(spark, d):
    return onehop_messages(G.co_purchase(spark, d), "triangles", pruning="both")[0]


_SENT = "s AS (SELECT src, count(*) AS d FROM g2 GROUP BY src)"


@query(f"WITH {O.G2}, {_SENT} SELECT 'none' AS pruning, count(*) AS messages, sum(s.d)::BIGINT AS ids_sent FROM g2 e JOIN s ON s.src = e.src UNION ALL SELECT 'smaller_ids', (SELECT count(*) FROM g2), (SELECT count(*) FROM g2 a JOIN g2 b ON a.dst = b.dst AND a.src < b.src)")
def w_onehop_messages(spark, d):
    """Messages and ids sent, without pruning and with receivers getting smaller ids only."""
    g = G.co_purchase(spark, d)
    rows = []
    for pruning in ("none", "smaller_ids"):
        counts = onehop_messages(g, "overlap", 12, pruning)[1]
        rows.append((pruning, counts["messages"], counts["ids_sent"]))
    return spark.createDataFrame(rows, "pruning string, messages long, ids_sent long")


@query(f"WITH {O.G2}, {_SENT} SELECT sum(d * d)::BIGINT AS ids_sent, 'over_budget' AS status FROM s")
def w_onehop_over_budget(spark, d):
    """The message form refused beyond a budget of ids."""
    _, counts = onehop_messages(G.co_purchase(spark, d), "ties", 20, budget=10)
    return spark.createDataFrame([(counts["ids_sent"], counts["status"])], "ids_sent long, status string")


# Tunings on and off give equal results
def _ablation(**options):
    def run(spark, d):
        g = G.co_purchase(spark, d)
        return sssp(g, _least_source(g), **options)[0]

    return run


_HOPS2 = ORACLES["w_sssp_hops"]
for _name, _options in {
    "full_patch": {"mode": "full", "apply": "patch"},
    "full_replace": {"mode": "full", "apply": "replace"},
    "incremental_replace": {"apply": "replace"},
    "incremental_patch": {"apply": "patch"},
    "cost": {"apply": "cost"},
    "sideways_semi": {"sideways": "semi"},
    "sideways_inlist": {"sideways": "inlist", "cached": False},
    "sideways_bloom": {"sideways": "bloom", "cached": False},
    "hint_merge": {"hint": "merge"},
    "hint_hash": {"hint": "shuffle_hash"},
}.items():
    query(_HOPS2, f"w_ablation_sssp_{_name}")(_ablation(**_options))


@query(ORACLES["w_triangles"])
def w_triangles_cost_based(spark, d):
    """Triangles as one SQL statement over an analysed, bucketed copy of the edges, in the join order the statistics give.

    A row of the copy is a cell of edges, so that the joins pair cells, and what they pair is closed as arrays: no wedge is a row.
    """
    g, name = G.co_purchase(spark, d), f"edges_{uuid.uuid4().hex[:8]}"
    halves = g.halves()
    cells = blocks.edge_cells(g.edges if halves is None else halves, halves is not None)
    if cells is None:
        return spark.createDataFrame([(0,)], "triangles long")
    with physical.settings(spark, spark__sql__classic__shuffleDependency__fileCleanup__enabled="true"):
        tables = layout.write_bucketed(replace(g, edges=cells), name, 4, by=("i",))
    e = tables["i"]
    physical.analyse(spark, e)

    def closed(one: pd.Series, two: pd.Series, three: pd.Series, four: pd.Series, five: pd.Series, six: pd.Series) -> pd.Series:
        return pd.Series([blocks.closed_cells(*row) for row in zip(one, two, three, four, five, six)], dtype="int64")

    spark.udf.register(f"closed_{name}", F.pandas_udf(closed, "long"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # Rows are large: a Python worker gets one at once.
    with physical.cost_based(spark), physical.settings(spark, spark__sql__execution__arrow__maxRecordsPerBatch=1):
        n = spark.sql(f"SELECT sum(closed_{name}(a1, a2, b1, b2, c1, c2)) AS triangles FROM (SELECT /*+ REPARTITION({parts}) */ a.one AS a1, a.two AS a2, b.one AS b1, b.two AS b2, c.one AS c1, c.two AS c2 FROM {e} a JOIN {e} b ON b.i = a.j JOIN {e} c ON c.i = a.i AND c.j = b.j)").first()[0]
    for t in tables.values():
        spark.sql(f"DROP TABLE {t}")
    spark.sql(f"DROP TEMPORARY FUNCTION closed_{name}")
    return spark.createDataFrame([(n or 0,)], "triangles long")


@query(f"WITH {O.G1D} SELECT dst AS id, round(sum(src * 0.5::DOUBLE), 6) AS value FROM g1d GROUP BY dst")
def w_user_functions(spark, d):
    """One round with a user's message expression and combiner as vectorised functions."""
    g = _g1(spark, d)
    values = g.vertices.select("id", F.col("id").cast("double").alias("value"))
    out = udf.gather(values, g.edges.withColumn("w", F.lit(0.5)), udf.message_udf(lambda v, w: v * w), udf.combine_udaf(lambda m: float(m.sum())))
    return out.select("id", F.round("value", 6).alias("value"))


@query(ORACLES["w_pagerank_10"])
def w_ablation_pagerank_kept_join(spark, d):
    return _rounded(pagerank(_g1(spark, d), eliminate_join=False))


@query(f"WITH {O.G1D}, s AS (SELECT dst AS id, min(src) AS m FROM g1d GROUP BY dst) SELECT v.id, s.m AS value FROM g1v v JOIN s USING (id) WHERE s.m < v.id")
def w_gather_apply(spark, d):
    """One step of a vertex function as an aggregate and a test: the smallest in-neighbour, where it is below the vertex."""
    g = _g1(spark, d)
    return gather_apply(g, g.vertices.select("id", F.col("id").alias("value")), VertexFunction(lambda v, w: v, "min", improves))


@query(f"WITH RECURSIVE {O.G2}, {O.levels('g2', _G2_FROM)} SELECT 'merge' AS join, count(dist) AS reached, sum(dist)::BIGINT AS total FROM d UNION ALL SELECT 'shuffle_hash', count(dist), sum(dist)::BIGINT FROM d UNION ALL SELECT 'broadcast', count(dist), sum(dist)::BIGINT FROM d")
def w_superstep_join_choice(spark, d):
    """The superstep engine with its fixed merge join, and with the choices it does not make."""
    g = G.co_purchase(spark, d)
    source, out = _least_source(g), None
    for join in ("merge", "shuffle_hash", "broadcast"):
        row = bsp_run(g, source, join=join)[0].agg(F.count("value").alias("reached"), F.sum("value").alias("total")).select(F.lit(join).alias("join"), "reached", "total")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def w_scaleout(spark, d):
    """Seconds of table-function runs on one task slot and on four: so many partitions, and shuffles of so many."""
    g = _g1(spark, d)
    n, rows = g.vertices.count(), []
    for slots in (1, 4):
        with physical.settings(spark, spark__sql__shuffle__partitions=slots, spark__sql__adaptive__coalescePartitions__parallelismFirst="false"):
            for name, program in (("pagerank", Ranking(n, 3)), ("sssp", ShortestPath(0))):
                t = time.time()
                run_program(g, program, "union", parts=slots)
                rows.append((name, slots, time.time() - t))
    return spark.createDataFrame(rows, "program string, slots long, seconds double")


@query(f"WITH {O.G2}, o AS (SELECT dst AS id, count(*) AS i FROM g2 GROUP BY dst), s AS (SELECT src AS id, count(*) AS o FROM g2 GROUP BY src) SELECT sum(i * o)::BIGINT AS wedges, sum(o * o)::BIGINT AS ids_sent FROM o JOIN s USING (id)")
def w_predicted_wedges(spark, d):
    """Rows of a one-hop join and ids of its message form, from degrees alone."""
    return M.predicted_wedges(G.co_purchase(spark, d))


@query("""WITH RECURSIVE e AS MATERIALIZED (SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.3),
ev AS (SELECT vec_id AS id FROM embeddings), """ + O.labels("e", "ev") + " SELECT id, component FROM c")
def w_embedding_components(spark, d):
    """Components of the vectors that are near each other."""
    return L.connected_components_star(G.embedding_neighbours(spark, d))


@query()
def w_cf(spark, d):
    """Error of collaborative filtering as a vertex program and by least squares, against the mean."""
    ratings = materialize(G.ratings(spark, d), "ratings", "zstd", free=True).df
    cells, out = rating_cells(ratings), None
    for method in ("vertex_program", "mllib"):
        row = collaborative_filtering(ratings, 8, 5, method, cells)[1].select(F.lit(method).alias("method"), "rmse", "rmse_mean")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT n.n_nationkey + 10000000000 AS id, 1::BIGINT AS dist FROM nation n WHERE n_regionkey = 0 UNION ALL SELECT c_custkey + 20000000000, 2 FROM customer JOIN nation ON n_nationkey = c_nationkey WHERE n_regionkey = 0 UNION ALL SELECT s_suppkey + 30000000000, 2 FROM supplier JOIN nation ON n_nationkey = s_nationkey WHERE n_regionkey = 0 UNION ALL SELECT 0, 0")
def w_geography_depth(spark, d):
    return sssp(G.geography(spark, d), 0)[0].where("dist is not null")


@query(f"WITH {O.G1D} SELECT (SELECT count(*) FROM g1v) AS vertices, (SELECT count(*) FROM g1d) AS edges, 0::BIGINT AS null_ids, 0::BIGINT AS duplicate_ids, 0::BIGINT AS null_ends, 0::BIGINT AS dangling_src, 0::BIGINT AS dangling_dst")
def w_integrity(spark, d):
    return _g1(spark, d).check_integrity()
