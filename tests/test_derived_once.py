"""Timed workloads derive their graphs once, not in every analysis they time."""

import pytest

from tidegraph import workloads as W
from tidegraph.plans.physical import settings
from tidegraph.sources import derived as G


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_scale_series_runs_over_written_graphs(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(W, "sssp", lambda g, source: seen.append(plan_of(g.edges)))
    monkeypatch.setattr(W, "pagerank", lambda g: g.vertices)
    monkeypatch.setattr(W.L, "connected_components_star", lambda g: g.vertices)
    assert W.w_scale_series(spark, sf).count() == 15
    assert len(seen) == 5 and not any("Join" in p or "Window" in p for p in seen)


def test_mixed_costs_lay_out_rows_of_the_written_graph(spark, sf, monkeypatch):
    class Seen(Exception):
        pass

    def layout(graph):
        raise Seen(plan_of(graph.edges) + plan_of(graph.vertices))

    monkeypatch.setattr(W, "row_layout", layout)
    with pytest.raises(Seen) as seen:
        W.w_mixed_costs(spark, sf)
    assert "Window" not in str(seen.value)


def test_lines_move_once_to_their_order(spark, sf):
    """Both sides of the join are one exchange, as are copies dropped; another takes the pairs."""
    with settings(spark, spark__sql__autoBroadcastJoinThreshold=-1):
        assert plan_of(G.co_purchase(spark, sf).edges).count("Exchange hashpartitioning") == 3
