"""Vector forms of vertex programs on graphs beyond what a barrier stage may hold."""

import pytest

from tests.test_graphs import graph, values
from tidegraph.vertexprog import runners
from tidegraph.vertexprog.api import Components, NeighbourTies, Ranking, ShortestPath
from tidegraph.vertexprog.runners import run_program

PAIRS = [(0, 1), (1, 2), (0, 2), (2, 3), (3, 1), (5, 6), (0, 1), (9, 0)]


@pytest.mark.parametrize("make", [lambda: ShortestPath(0), lambda: Ranking(9, 4), Components], ids=["sssp", "pagerank", "components"])
def test_large_graphs_run_by_rounds(spark, monkeypatch, make):
    """With parallel edges, a vertex without any and one that no edge leads to."""
    monkeypatch.setattr(runners, "BARRIER_ROWS", 1)
    g = graph(spark, PAIRS, range(9 if make is not Components else 10))
    got, report = run_program(g, make(), "barrier")
    want = values(run_program(g, make(), "union")[0])
    assert set(want) == set(values(got)) and all(v == pytest.approx(want[k]) for k, v in values(got).items())
    assert report.rounds and (make is not Components or report.converged)


def test_programs_without_a_vector_form_are_refused(spark, monkeypatch):
    monkeypatch.setattr(runners, "BARRIER_ROWS", 1)
    with pytest.raises(ValueError):
        run_program(graph(spark, PAIRS), NeighbourTies(), "barrier")
