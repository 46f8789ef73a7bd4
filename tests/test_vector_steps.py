"""Vector steps of united and joined input give what stepping vertex by vertex gives."""

import pytest

from tidegraph.graph import PropertyGraph
from tidegraph.vertexprog import runners
from tidegraph.vertexprog.api import Components, Ranking, ShortestPath
from tidegraph.vertexprog.runners import run_program


def _graph(spark):
    import random

    draw = random.Random(4)
    edges = [(draw.randrange(1, 60), draw.randrange(1, 60), float(draw.randrange(1, 9))) for _ in range(200)]
    edges += [*edges[:20], (3, 3, 1.0), (5, 999, 2.0), (6, None, 1.0), (7, 61, 2.0), *[(2, x, 4.0) for x in range(1, 60)]]
    return PropertyGraph(spark.createDataFrame([(x,) for x in range(1, 64)], "id long"), spark.createDataFrame(edges, "src long, dst long, weight double"))


@pytest.mark.parametrize("input, program", [("union", Ranking(63, 3)), ("join", Ranking(63, 3)), ("union", ShortestPath(1, True)), ("join", Components())], ids=["united_ranks", "joined_ranks", "united_weights", "joined_labels"])
def test_vector_steps_equal_steps_by_vertex(spark, monkeypatch, input, program):
    monkeypatch.setattr(runners, "VECTOR_ROWS", 5)
    g, out = _graph(spark), []
    for vectors in (True, False):
        if not vectors:
            monkeypatch.setattr(runners, "_has_vectors", lambda program, kind: False)
        states, report = run_program(g, program, input, "weight", 3, batch_vertices=3)
        out.append(({r["id"]: r["state"] for r in states.collect()}, [(r["updates"], r["messages"]) for r in report.rounds], report.converged))
    assert out[0][0] == pytest.approx(out[1][0], nan_ok=True) and len(out[0][0]) == 63
    assert out[0][1:] == out[1][1:]


@pytest.mark.parametrize("input", ["union", "join", "resident"])
def test_a_program_with_a_vector_form_is_not_stepped_by_vertex(spark, input):
    class Told(Ranking):
        def compute(self, *args):
            raise AssertionError("stepped by vertex")

    no_edges = PropertyGraph(spark.range(1, 5), spark.createDataFrame([], "src long, dst long"))
    assert {round(r["state"], 9) for r in run_program(no_edges, Told(4, 3), input)[0].collect()} == {0.0375}
    assert run_program(_graph(spark), Told(63, 2), input)[0].count() == 63


@pytest.mark.parametrize("input", ["union", "join"])
def test_few_edges_are_few_parts_and_listed_once(spark, monkeypatch, input):
    """A superstep does not start a function in each of the session's shuffle partitions."""
    seen, name = [], f"_{input}_step"
    usual = getattr(runners, name)

    def step(vertices, edges, *args):
        seen.append((edges.rdd.getNumPartitions(), edges.columns, edges.is_cached))
        return usual(vertices, edges, *args)

    monkeypatch.setattr(runners, name, step)
    run_program(_graph(spark), Ranking(63, 3), input)
    columns = ["id", "edges"] if input == "join" else ["id", "dst", "w"]
    assert len(seen) == 4 and all(x == (1, columns, True) for x in seen)
