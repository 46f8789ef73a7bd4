"""Analyses over blocks against brute force, and the rows they do not make."""

import random

import numpy as np
import pyarrow.compute as pc
import pytest

from tests.test_graphs import graph, values
from tidegraph.baselines.engines import onehop_messages
from tidegraph.graph import PropertyGraph
from tidegraph.operators import blocks, motifs as M
from tidegraph.runtime import materialize


def pairs_of(n: int, m: int, seed: int, spread: int = 1) -> list:
    rng = random.Random(seed)
    return [(a * spread, b * spread) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(m)) if a != b]


def neighbours(pairs) -> dict:
    near: dict = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    return near


def triangles_of(near) -> dict:
    return {v: sum(b in near[a] for a in own for b in own if a < b) for v, own in near.items()}


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(params=["one band", "several bands", "remainders"])
def small(request, spark, monkeypatch):
    """A graph with negative ids, and bands of so few edges that tasks take one, two and three of them; with one id far away, bins are remainders."""
    pairs = [(a - 7, b - 7) for a, b in pairs_of(60, 400, 1)]
    if request.param != "one band":
        monkeypatch.setattr(blocks, "BAND_EDGES", 60)
        monkeypatch.setattr(blocks, "WEDGES", 50)
    if request.param == "remainders":
        pairs += [(1 << 45, 1), (1 << 45, 2)]
    return pairs, graph(spark, pairs, directed=False)


def test_triangles_in_blocks(small):
    pairs, g = small
    want = triangles_of(neighbours(pairs))
    for orient in ("degree", "id"):
        assert values(M.triangle_count(g, True, orient)) == want
        assert M.triangle_count(g, orient=orient).first()[0] * 3 == sum(want.values())
    assert "Join" not in plan_of(M.triangle_count(g))


def test_triangles_ignore_loops_and_parallel_edges(spark):
    pairs = [(0, 1), (1, 0), (0, 1), (1, 2), (2, 0), (2, 2)]
    assert values(M.triangle_count(graph(spark, pairs), True)) == {0: 1, 1: 1, 2: 1}


def test_clustering_in_blocks(small):
    pairs, g = small
    near = neighbours(pairs)
    for v, n in triangles_of(near).items():
        d = len(near[v])
        want = 2 * n / (d * (d - 1)) if d > 1 else 0.0
        near[v] = want
    assert values(M.clustering(g)) == near


def test_weak_ties_in_blocks(small):
    pairs, g = small
    near = neighbours(pairs)
    closed = triangles_of(near)
    want = {v: n for v in near if (n := len(near[v]) * (len(near[v]) - 1) // 2 - closed[v]) > 40}
    for form in ("identity", "anti", "left"):
        assert values(M.weak_ties(g, 40, form=form)) == want
        assert "LeftAnti" not in plan_of(M.weak_ties(g, 40, form=form))


@pytest.mark.parametrize("measure,threshold", [("count", 3), ("jaccard", 0.15), ("cosine", 0.3), ("min", 0.35), ("adamic", 1.5)])
def test_overlap_in_blocks(small, measure, threshold):
    import math

    pairs, g = small
    near, want = neighbours(pairs), {}
    for a in near:
        for b in near:
            both, d, e = near[a] & near[b], len(near[a]), len(near[b])
            n = len(both)
            value = {"count": n, "jaccard": n / (d + e - n), "cosine": n / math.sqrt(d * e), "min": n / min(d, e), "adamic": round(sum(1 / math.log(len(near[x]) + 1) for x in both), 6)}[measure]
            if a < b and value > threshold:
                want[a, b] = (n, value)
    got = M.strong_overlap(g, threshold, measure=measure)
    # In-degrees alone are counted by an aggregate.
    assert len(want) > 5 and "partial_sum" not in plan_of(got) and plan_of(got).count("partial_count") <= (measure == "adamic")
    assert {(r.n1, r.n2): (r.common, r.common if measure == "count" else round(r.value, 6) if measure == "adamic" else r.value) for r in got.collect()} == want


def test_overlap_counts_parallel_edges(spark):
    """As the join does, also in its own band."""
    g = PropertyGraph(spark.range(4), spark.createDataFrame([(0, 3), (0, 3), (1, 3), (1, 3), (2, 3)], "src long, dst long"))
    assert {(r.n1, r.n2): r.common for r in M.strong_overlap(g, 0).collect()} == {(0, 1): 4, (0, 2): 2, (1, 2): 2}
    assert M.strong_overlap(g, 0, measure="jaccard").where("common <> 1").count() == 0


def test_string_ids_keep_the_join(spark):
    g = PropertyGraph(spark.createDataFrame([("a",), ("b",), ("c",)], "id string"), spark.createDataFrame([("a", "c"), ("b", "c")], "src string, dst string"))
    assert [tuple(r) for r in M.strong_overlap(g, 0).collect()] == [("a", "b", 1)] and M.triangle_count(g).first()[0] == 0


@pytest.mark.parametrize("task", ["overlap", "ties", "triangles"])
def test_message_forms_explode_no_lists(spark, task):
    pairs = pairs_of(40, 300, 4)
    g = graph(spark, pairs, directed=False)
    near = neighbours(pairs)
    got, counts = onehop_messages(g, task, 5, "smaller_ids" if task != "triangles" else "both")
    assert "near#" not in plan_of(got)
    if task == "overlap":
        assert {(r.n1, r.n2): r.common for r in got.collect()} == {(a, b): n for a in near for b in near if a < b and (n := len(near[a] & near[b])) > 5}
        assert counts["messages"] == sum(len(x) for x in near.values())
    elif task == "triangles":
        assert got.first()[0] * 3 == sum(triangles_of(near).values())
    else:
        closed = triangles_of(near)
        assert values(got) == {v: n for v in near if (n := len(near[v]) * (len(near[v]) - 1) // 2 - closed[v]) > 5}


def test_written_edges_leave_no_shuffle_files(spark):
    def shuffles():
        files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {name for k in range(files.size()) if (name := files.apply(k).getName()).startswith("shuffle_")}

    moved, before = spark.range(1000).selectExpr("id % 10 as k", "id").repartition(3, "k"), shuffles()
    materialize(moved, free=True)
    assert not shuffles() - before
    materialize(moved)
    assert shuffles() - before


@pytest.mark.parametrize("measure,threshold", [("count", 5), ("jaccard", 0.25), ("cosine", 0.4), ("min", 0.5), ("adamic", 2.0)])
def test_sources_with_counters_of_their_own(spark, monkeypatch, measure, threshold):
    """All, those with many wedges, or none of them: a dense part beside a sparse one."""
    import math

    pairs = list(set(pairs_of(60, 900, 3))) + [(100 + k, 160 + k) for k in range(50)]
    near, want = neighbours(pairs), {}
    for a in near:
        for b in near:
            both, d, e = near[a] & near[b], len(near[a]), len(near[b])
            n = len(both)
            value = {"count": n, "jaccard": n / (d + e - n), "cosine": n / math.sqrt(d * e), "min": n / min(d, e), "adamic": sum(1 / math.log(len(near[x]) + 1) for x in both)}[measure]
            if a < b and value > threshold:
                want[a, b] = n
    g, usual = graph(spark, pairs, directed=False), blocks._dense
    for form in (usual, lambda per, edges, others: per >= 0, lambda per, edges, others: per < 0):
        monkeypatch.setattr(blocks, "_dense", form)
        assert {(r.n1, r.n2): r.common for r in M.strong_overlap(g, threshold, measure=measure).collect()} == want and len(want) > 5
    per, edges = np.array([1000, 1000, 3]), np.array([10, 100, 2])
    assert usual(per, edges, 2000).tolist() == [True, False, False] and not usual(per, edges, 5000).any()


@pytest.mark.parametrize("ranges", [True, False])
def test_cells_of_edges_hold_every_triangle_once(spark, monkeypatch, ranges):
    import itertools
    import random

    draw = random.Random(8)
    pairs = {(draw.randrange(40), draw.randrange(40)) for _ in range(260)}
    monkeypatch.setattr(blocks, "BAND_EDGES", 60 if ranges else 8)
    near = {frozenset(p) for p in pairs if p[0] != p[1]}
    wanted = sum(all(frozenset(p) in near for p in itertools.combinations(three, 2)) for three in itertools.combinations(range(40), 3))
    rows = blocks.edge_cells(spark.createDataFrame([*pairs, *[(b, a) for a, b in pairs], (1, None)], "src long, dst long")).collect()
    assert sum(r["n"] for r in rows) == len(near) and all(r["i"] <= r["j"] for r in rows) and len({r["i"] for r in rows}) > 2
    found = sum(blocks.closed_cells(a["one"], a["two"], b["one"], b["two"], c["one"], c["two"]) for a in rows for b in rows for c in rows if b["i"] == a["j"] and c["i"] == a["i"] and c["j"] == b["j"])
    assert found == wanted > 50


def test_pairs_of_unequal_degrees_do_not_all_reach_the_measure(spark, monkeypatch):
    """The fewest common targets follow from both degrees: pairs that can't pass are left before they are arrays."""
    rng, seen = np.random.default_rng(4), []
    near = rng.random((200, 400)) < 0.1
    near[0] = False
    near[0, 0] = True  # a source with one target, which alone would let almost every pair through
    src, dst = np.nonzero(near)
    common = near.astype(int) @ near.T.astype(int)
    size = near.sum(1)
    want = {(a, b): int(common[a, b]) for a in range(200) for b in range(a + 1, 200) if common[a, b] / np.sqrt(size[a] * size[b]) > 0.25}
    made = {}
    monkeypatch.setattr(blocks, "_dense", lambda per, edges, others: per >= 0)
    from pyspark.sql.pandas.group_ops import PandasGroupedOpsMixin as Grouped

    def held(self, function, schema):
        made["count"], made["dealt"] = function, self._df
        return usual(self, function, schema)

    usual = Grouped.applyInArrow
    monkeypatch.setattr(Grouped, "applyInArrow", held)

    def keep(n, value, d1, d2):
        seen.append(len(n))
        return n / np.sqrt(d1 * d2) > 0.25

    edges = spark.createDataFrame([(int(a), int(b) + 1000) for a, b in zip(src, dst)], "src long, dst long")
    blocks.common_neighbours(edges, keep)
    dealt, out = made["dealt"].toArrow(), {}
    for task in set(dealt["task"].to_pylist()):
        found = made["count"](dealt.filter(pc.equal(dealt["task"], task))).to_pylist()
        out |= {(r["n1"], r["n2"]): r["common"] for r in found if r["n2"] is not None}
    # A task knows degrees in part, and so may keep more.
    assert {k: n for k, n in out.items() if n / np.sqrt(size[k[0]] * size[k[1]]) > 0.25} == want and len(want) > 5
    assert max(seen) < 0.2 * (common > 0).sum() / 2


@pytest.mark.parametrize("low,high", [(0, 3), (-5, 1 << 40), (-(1 << 62), 1 << 62)])
def test_arrays_pack_sort_and_number_as_they_should(low, high):
    rng = np.random.default_rng(2)
    one, two = rng.integers(low, high, 3000), rng.integers(low, high, 3000)
    assert (blocks._unpacked(blocks._packed(one)) == one).all() and len(blocks._unpacked(blocks._packed(one[:0]))) == 0
    each = np.unique(np.stack([one, two], 1), axis=0)
    a, b = blocks._ordered(one, two, distinct=True)
    assert (a == each[:, 0]).all() and (b == each[:, 1]).all()
    ids, at = blocks._numbered(one)
    assert (ids[at] == one).all() and (np.diff(ids) > 0).all()


def test_equal_entries_are_found_by_sorting():
    """Hashing them, as ``np.unique`` does, took thirty times as long on a few million."""
    import time

    one, two = np.random.default_rng(1).integers(0, 20_000, (2, 1_500_000))
    blocks._ordered(one[:1000], two[:1000], distinct=True)
    t = time.process_time()
    blocks._ordered(one, two, distinct=True)
    sorting, t = time.process_time() - t, time.process_time()
    np.lexsort((two, one))
    assert sorting < (time.process_time() - t)
