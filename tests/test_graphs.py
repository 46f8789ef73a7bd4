"""Hand-made graphs, closed forms, invariants and counterexamples."""

import pytest
from pyspark.sql import functions as F

from tidegraph.baselines.engines import async_run, bsp_run, onehop_messages
from tidegraph.graph import PropertyGraph
from tidegraph.operators import labels as L, motifs as M
from tidegraph.operators.components import star_components
from tidegraph.operators.pagerank import pagerank
from tidegraph.operators.sssp import khop, sssp, sssp_local_rounds
from tidegraph.plans.iterate import VertexState, counted
from tidegraph.sources import derived as G

PATH = [(0, 1), (1, 2), (2, 3), (3, 4)]
TWO_TRIANGLES = [(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (2, 4)]
ZIGZAG = [(4, 3), (2, 3), (2, 1), (0, 1)]


def graph(spark, pairs, vertices=None, directed=True):
    edges = spark.createDataFrame(pairs, "src long, dst long") if pairs else spark.createDataFrame([], "src long, dst long")
    ids = sorted(vertices if vertices is not None else {x for p in pairs for x in p})
    g = PropertyGraph(spark.createDataFrame([(i,) for i in ids], "id long"), edges, directed)
    return g if directed else g.symmetrised()


def values(df, key="id"):
    other = [c for c in df.columns if c != key][0]
    return {r[key]: r[other] for r in df.collect()}


@pytest.mark.parametrize("options", [{}, {"mode": "full", "apply": "replace"}, {"apply": "patch"}, {"apply": "auto", "switch_at": 2}, {"apply": "cost"}, {"sideways": "inlist"}])
def test_path_distances(spark, options):
    out, report = sssp(graph(spark, PATH, range(6)), 0, **options)
    assert values(out) == {0: 0, 1: 1, 2: 2, 3: 3, 4: 4, 5: None}
    assert report.converged and [r["updates"] for r in report.rounds] == [1, 1, 1, 1, 0]


def test_weighted_distances_take_the_cheaper_way(spark):
    edges = spark.createDataFrame([(0, 1, 5.0), (0, 2, 1.0), (2, 1, 1.5)], "src long, dst long, weight double")
    g = PropertyGraph(spark.range(3), edges)
    assert {k: float(v) for k, v in values(sssp(g, 0, "weight")[0]).items()} == {0: 0.0, 1: 2.5, 2: 1.0}


def test_absent_source_and_bounded_depth(spark):
    assert set(values(sssp(graph(spark, PATH), 99)[0]).values()) == {None}
    near = values(sssp(graph(spark, PATH), 0, max_depth=2)[0])
    assert near[2] == 2 and near[3] is None


def test_local_rounds_need_fewer_exchanges(spark):
    g = graph(spark, [(i, i + 1) for i in range(12)])
    out, rounds = sssp_local_rounds(g, 0, parts=1, local_rounds=4)
    assert values(out)[12] == 12 and rounds <= 5


def test_khop(spark):
    g = khop(graph(spark, PATH), 1, 2)
    assert {tuple(r) for r in g.edges.collect()} == {(1, 2), (2, 3)}


def test_components_of_every_direction(spark):
    g = graph(spark, [*ZIGZAG, (7, 6)], range(9))
    want = {0: 0, 1: 0, 2: 0, 3: 0, 4: 0, 5: 5, 6: 6, 7: 6, 8: 8}
    assert values(L.connected_components(g)[0]) == want
    assert values(L.connected_components(g, "alternate", full_rounds=0)[0]) == want
    assert values(L.connected_components_star(g)) == want
    forward = values(L.connected_components(g, "forward")[0])
    assert forward[3] == 2 and forward[6] == 6 and forward[1] == 0


def test_literal_frontier_loses_labels(spark):
    g = graph(spark, PATH)
    exact = values(L.connected_components(g, "alternate", full_rounds=0)[0])
    literal = values(L.connected_components(g, "alternate", full_rounds=0, frontier="literal")[0])
    assert set(exact.values()) == {0} and literal != exact


def test_star_components_of_a_long_path(spark):
    links = spark.range(60).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert set(values(star_components(links)).values()) == {0}
    assert star_components(links.limit(0)).count() == 0


def test_rank_sums_and_bounds(spark):
    g = graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3)], range(5))
    ranks = values(pagerank(g, sources="redistribute", rounds=30))
    assert abs(sum(ranks.values()) - 1) < 1e-9
    standard = values(pagerank(g))
    assert min(standard.values()) >= 0.15 / 5 - 1e-12 and set(standard) == set(range(5))
    assert set(values(pagerank(g, sources="literal", rounds=1))) == {0, 1, 2, 3}
    g.dst_in_vertices = True
    assert values(pagerank(g)) == standard


def test_triangles_overlap_and_ties(spark):
    g = graph(spark, TWO_TRIANGLES, directed=False)
    assert M.triangle_count(g).first()[0] == 2 == M.triangle_count(g, orient="id").first()[0]
    assert sum(values(M.triangle_count(g, True)).values()) == 6
    for form in ("left", "anti", "identity"):
        assert values(M.weak_ties(g, 3, form=form)) == {2: 4}
    assert values(M.weak_ties(g, 4, strict=False)) == {2: 4}
    pairs = {(r.n1, r.n2): r.common for r in M.strong_overlap(g, 0).collect()}
    assert pairs[0, 1] == 1 and pairs[0, 3] == 1
    assert values(M.clustering(g))[0] == 1.0


def test_message_forms_agree_and_refuse_lossy_pruning(spark):
    g = graph(spark, TWO_TRIANGLES, directed=False)
    want = {(r.n1, r.n2): r.common for r in M.strong_overlap(g, 0).collect()}
    for pruning in ("none", "smaller_ids"):
        found, counts = onehop_messages(g, "overlap", 0, pruning)
        assert {(r.n1, r.n2): r.common for r in found.collect()} == want
    for pruning in ("none", "higher_id", "smaller_ids", "both"):
        assert onehop_messages(g, "triangles", pruning=pruning)[0].first()[0] == 2
    assert values(onehop_messages(g, "ties", 3)[0]) == {2: 4}
    with pytest.raises(ValueError):
        onehop_messages(g, "overlap", 0, "higher_id")
    lossy = {(r.n1, r.n2): r.common for r in onehop_messages(g, "overlap", 0, "both", allow_lossy=True)[0].collect()}
    assert sum(lossy.values()) < sum(want.values())
    assert onehop_messages(g, "ties", budget=3)[1]["status"] == "over_budget"


def test_baselines_agree_with_plans(spark):
    g = graph(spark, [(0, 1), (1, 2), (0, 2), (2, 3)], range(5))
    want = values(sssp(g, 0)[0])
    assert values(bsp_run(g, 0)[0]) == want
    assert values(async_run(g, 0)[0]) == want


def test_state_patches_then_replaces(spark):
    state = VertexState(spark.range(10).select("id", F.lit(9).cast("bigint").alias("value")), "auto", switch_at=3)
    small, n = counted(spark.createDataFrame([(1, 5)], "id long, value long"), "d")
    assert state.apply(small, n) == "patch" and values(state.current())[1] == 5
    more, n = counted(spark.createDataFrame([(1, 4), (2, 4)], "id long, value long"), "d")
    assert state.apply(more, n) == "replace" and values(state.current()) == {i: 4 if i in (1, 2) else 9 for i in range(10)}


def test_integrity_counts(spark):
    g = PropertyGraph(spark.createDataFrame([(1,), (1,), (None,)], "id long"), spark.createDataFrame([(1, 2), (None, 1)], "src long, dst long"))
    row = g.check_integrity().first()
    assert (row.duplicate_ids, row.null_ids, row.null_ends, row.dangling_dst, row.dangling_src) == (1, 1, 1, 1, 0)


def test_empty_graph(spark):
    g = graph(spark, [], [])
    assert sssp(g, 0)[0].count() == 0 and pagerank(g).count() == 0 and L.connected_components(g)[0].count() == 0
    assert M.triangle_count(g).first()[0] == 0


def test_closed_forms_on_the_tables(spark, sf):
    replies = G.replies(spark, sf)
    turns = values(sssp(replies, 0)[0])
    assert all(turns[i] == i for i in turns if i < 1000 and turns[i] is not None) and turns[0] == 0
    depth = values(sssp(G.geography(spark, sf), 0)[0])
    assert {v for v in depth.values() if v is not None} == {0, 1, 2}
    copies = G.duplicates(spark, sf)
    assert len(set(values(L.connected_components_star(copies)).values())) == 189


def test_level_sizes_of_the_slice(spark, sf):
    g = G.co_purchase(spark, sf, sliced=True)
    source = g.edges.agg(F.min("src")).first()[0]
    _, report = sssp(g, source)
    assert [r["updates"] for r in report.rounds] == [4, 3, 5, 15, 37, 30, 10, 0]
    assert M.triangle_count(g).first()[0] == 414 and M.strong_overlap(g, 4).count() == 107 and M.weak_ties(g, 20).count() == 20


def test_embedding_components_match_brute_force(spark, sf):
    """Every pair at the threshold counts, also across blocks."""
    import numpy as np

    rows = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding").collect()
    v = np.array([r.embedding for r in rows], dtype=np.float64)
    v /= np.linalg.norm(v, axis=1)[:, None]
    for least in (0.3, 0.4):
        near = v @ v.T >= least
        want, seen = {}, set()
        for i in sorted(range(len(rows)), key=lambda k: rows[k].vec_id):
            waiting = [] if i in seen else [i]
            seen.update(waiting)
            while waiting:
                j = waiting.pop()
                want[rows[j].vec_id] = rows[i].vec_id
                fresh = set(np.flatnonzero(near[j]).tolist()) - seen
                seen |= fresh
                waiting += fresh
        g = G.embedding_neighbours(spark, sf, least, block=64)
        got = {r.id: r.component for r in L.connected_components_star(g).collect()}
        assert {i: got.get(i, i) for i in want} == want


def test_hub_sources_are_split(spark, monkeypatch):
    """A star's edges lie in several partitions and every analysis gives what it gives without the split."""
    from tidegraph.plans import layout

    pairs = [(0, i) for i in range(1, 60)] + [(i, i + 1) for i in range(1, 80)] + [(7, 0), (200, 201)]
    g = graph(spark, pairs)
    want = [values(sssp(g, 0)[0]), values(sssp(g, 0, mode="full")[0]), values(pagerank(g)), values(L.connected_components(g)[0]), values(L.connected_components(g, "alternate")[0])]
    monkeypatch.setattr(layout, "HUB_EDGES", 4)
    monkeypatch.setattr(layout, "FEW_EDGES", 10)
    dealt = layout.DealtEdges(g.edges)
    places = dealt.df.where("src = 0").groupBy(F.spark_partition_id()).count().collect()
    assert dealt.hubs is not None and len(places) > 1 and dealt.meet(spark.createDataFrame([(0, "x")], "src long, v string")).count() == 59
    got = [values(sssp(g, 0)[0]), values(sssp(g, 0, mode="full")[0]), values(pagerank(g)), values(L.connected_components(g)[0]), values(L.connected_components(g, "alternate")[0])]
    assert got[:2] == want[:2] and got[3:] == want[3:]
    assert all(abs(got[2][k] - v) < 1e-12 for k, v in want[2].items())


def test_rounds_leave_no_deltas_behind(spark):
    """What a run wrote and no longer needs goes as it proceeds, whatever its number of rounds."""
    import os

    from tidegraph.runtime import scratch_root

    folder = scratch_root(spark).removeprefix("file:") + "/tables"
    os.makedirs(folder, exist_ok=True)
    chain = graph(spark, [(i, i + 1) for i in range(14)])
    for run in (lambda: sssp(chain, 0), lambda: sssp(chain, 0, apply="patch"), lambda: L.connected_components(chain, "alternate"), lambda: bsp_run(chain, 0)):
        before = set(os.listdir(folder))
        run()
        left = [x for x in os.listdir(folder) if x not in before and x.split("-")[0] in ("delta", "overlay", "state", "messages", "bsp")]
        assert len(left) <= 6, left


def test_weak_ties_close_from_the_end_back_to_the_start(spark):
    g = graph(spark, [(0, 1), (1, 2), (2, 0), (3, 1), (3, 2)])
    # Through 1: 0 -> 2 is closed by 2 -> 0; 3 -> 2 is open, as nothing leads from 2 to 3. Through 0: 2 -> 1 is closed by 1 -> 2.
    for form in ("anti", "left"):
        assert values(M.weak_ties(g, 0, form=form)) == {1: 1, 2: 1}


def test_shared_memory_ranks(spark):
    g = graph(spark, TWO_TRIANGLES + [(4, 0)])
    got, report = async_run(g, kind="pagerank", parts=3)
    assert all(abs(v - values(pagerank(g))[k]) < 1e-12 for k, v in values(got).items()) and set(report.phases) == {"load", "analysis", "store"}


def test_ranks_settle_within_the_tolerance(spark):
    g = graph(spark, TWO_TRIANGLES + [(4, 0)])
    loose, exact = values(pagerank(g, rounds=100, tol=1e-6)), values(pagerank(g, rounds=100))
    assert all(abs(v - loose[k]) < 1e-5 for k, v in exact.items()) and loose != exact
