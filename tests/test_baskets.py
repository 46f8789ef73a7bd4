"""Pairs of items that share a basket against brute force, and the block forms over them."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from tests.test_blocks import neighbours, triangles_of
from tests.test_graphs import values
from tidegraph.baselines.engines import onehop_messages
from tidegraph.graph import PropertyGraph
from tidegraph.operators import motifs as M
from tidegraph.sources import baskets, derived as G


def lines_of(shift: int) -> list:
    rng = random.Random(5)
    rows = [(rng.randrange(60), rng.randrange(-9, 30)) for _ in range(400)]
    # One item in every basket, repeated lines, a far item, and ends that are null.
    return rows + rows[:50] + [(b, 3) for b in range(60)] + [(1, shift), (2, shift), (None, 5), (5, None)]


def pairs_of(lines) -> set:
    held: dict = {}
    for basket, item in lines:
        if basket is not None and item is not None:
            held.setdefault(basket, set()).add(item)
    return {p for items in held.values() for p in itertools.combinations(sorted(items), 2)}


@pytest.mark.parametrize("shift", [40, 1 << 45])
@pytest.mark.parametrize("small", [False, True])
def test_pairs_are_all_there_once(spark, monkeypatch, shift, small):
    """Also where cells are split by the other end, baskets go over chunks and a basket is larger than one."""
    if small:
        monkeypatch.setattr(baskets, "CELL_LINES", 7)
        monkeypatch.setattr(baskets, "DEAL_ROWS", 5)
    lines = lines_of(shift)
    got = baskets.item_pairs(spark.createDataFrame(lines, "basket long, item long")).collect()
    assert len(got) == len(set(got)) and {tuple(r) for r in got} == pairs_of(lines)


def test_no_lines_give_none(spark):
    assert baskets.item_pairs(spark.createDataFrame([(None, 1)], "basket long, item long")) is None


def test_halves_are_the_edges(spark, sf):
    for sliced in (False, True):
        g = G.co_purchase(spark, sf, sliced=sliced)
        once = g.halves()
        assert g.halves() is once
        assert {tuple(r) for r in M.both_ways(once).collect()} == {tuple(r) for r in g.edges.collect()}
        assert PropertyGraph(g.vertices, g.edges.where("src < 100"), False, once=g.once).halves() is None


def test_block_forms_read_each_edge_once(spark):
    """They do not touch the edges both ways, which would be derived and shuffled again."""
    pairs = sorted(pairs_of(lines_of(40)))
    near = neighbours(pairs)
    ids = spark.createDataFrame([(v,) for v in near], "id long")
    written = spark.createDataFrame(pairs, "src long, dst long")
    edges = written.select(F.expr("cast(raise_error('derived again') as bigint)").alias("src"), "dst")

    def made():
        return PropertyGraph(ids, edges, False, True, simple=True, once=(edges, lambda: written))

    closed = triangles_of(near)
    ties = {v: n for v in near if (n := len(near[v]) * (len(near[v]) - 1) // 2 - closed[v]) > 40}
    common = {(a, b): n for a in near for b in near if a < b and (n := len(near[a] & near[b])) > 8}
    assert ties and common
    assert values(M.triangle_count(made(), True)) == closed and M.triangle_count(made(), orient="id").first()[0] * 3 == sum(closed.values())
    assert {r.id: round(r.coefficient, 9) for r in M.clustering(made()).collect()} == {v: round(2 * closed[v] / (d * (d - 1)), 9) if (d := len(near[v])) > 1 else 0 for v in near}
    assert values(M.weak_ties(made(), 40)) == values(M.weak_ties(made(), 40, form="identity")) == ties
    assert {(r.n1, r.n2): r.common for r in M.strong_overlap(made(), 8).collect()} == common
    for measure, least in (("jaccard", 0.3), ("adamic", 2.0)):
        plain = PropertyGraph(ids, M.both_ways(written), False, True, simple=True)
        rows = [{(r.n1, r.n2): (r.common, round(r.value, 9)) for r in M.strong_overlap(g, least, measure=measure).collect()} for g in (made(), plain)]
        assert rows[0] and rows[0] == rows[1]
    for task, want in (("overlap", common), ("ties", ties)):
        got, counts = onehop_messages(made(), task, 8 if task == "overlap" else 40)
        assert {(r.n1, r.n2): r.common for r in got.collect()} == want if task == "overlap" else values(got) == want
        assert counts["messages"] == 2 * len(pairs) and counts["ids_sent"] == sum(len(x) ** 2 for x in near.values())
