"""Collaborative filtering over cells of ratings gives what its messages give."""

import random

import pytest

from tidegraph.vertexprog import cells, cf
from tidegraph.vertexprog.api import Factors
from tidegraph.vertexprog.runners import run_program


def test_cells_give_the_factors_of_the_messages(spark, monkeypatch):
    monkeypatch.setattr(cells, "CELL_RATINGS", 40)
    draw = random.Random(6)
    pairs = {(draw.randrange(30), draw.randrange(20)) for _ in range(150)} | {(7, x) for x in range(60)}
    rated = spark.createDataFrame([(u, i, float(draw.randrange(1, 6))) for u, i in sorted(pairs)], "user long, item long, rating double")
    mean = rated.agg({"rating": "avg"}).first()[0]
    wanted = {r["id"]: r["state"] for r in run_program(cf.rating_graph(rated), Factors(3, 2, centre=mean), "union", "weight")[0].collect()}
    dealt = cf.rating_cells(rated)
    assert dealt.written.df.count() > 4
    factors, errors = cf.collaborative_filtering(rated, 3, 2, cells=dealt)
    found = {r["id"]: r["factors"] for r in factors.collect()}
    assert found.keys() == wanted.keys()
    for k, x in wanted.items():
        assert found[k] == pytest.approx(x, abs=1e-9)
    off = [(r["rating"] - mean - sum(a * b for a, b in zip(wanted[r["user"]], wanted[r["item"] + cf.ITEM_OFFSET])), r["rating"] - mean) for r in rated.collect()]
    row = errors.first()
    assert row["rmse"] == pytest.approx((sum(a * a for a, _ in off) / len(off)) ** 0.5) and row["rmse_mean"] == pytest.approx((sum(b * b for _, b in off) / len(off)) ** 0.5)
