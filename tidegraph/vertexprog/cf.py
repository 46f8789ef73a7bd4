"""Collaborative filtering by a vertex program or by alternating least squares."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.vertexprog.api import Factors
from tidegraph.vertexprog.cells import RatingCells, run_factors

ITEM_OFFSET = 1_000_000_000


def rating_graph(ratings: DataFrame) -> PropertyGraph:
    """``(user, item, rating)`` as a bipartite graph with both orientations; item ids are offset."""
    r = ratings.select(F.col("user").alias("src"), (F.col("item") + ITEM_OFFSET).alias("dst"), F.col("rating").cast("double").alias("weight"))
    return PropertyGraph.of_edges(r.unionByName(r.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")), directed=False)


def collaborative_filtering(ratings: DataFrame, rank: int = 8, rounds: int = 10, method: str = "vertex_program", cells: RatingCells | None = None) -> tuple[DataFrame, DataFrame]:
    """``(id, factors)`` and a row ``rmse, rmse_mean``: the error of the factors and that of always predicting the mean.

    Ratings are dealt out to ``cells`` unless they are already (see ``rating_cells``); the vertex program runs over these and makes no message a row.
    """
    cells = cells or rating_cells(ratings)
    names = [f"f{k}" for k in range(rank)]
    if method == "mllib":
        from pyspark.ml.recommendation import ALS

        model = ALS(rank=rank, maxIter=rounds, userCol="user", itemCol="item", ratingCol="rating", seed=5, regParam=0.1).fit(ratings.select(F.col("user").cast("int"), F.col("item").cast("int"), "rating"))
        both = model.userFactors.select(F.col("id").cast("long"), "features").unionByName(model.itemFactors.select((F.col("id") + ITEM_OFFSET).cast("long").alias("id"), "features"))
        states, centre = both.select("id", *[F.col("features")[k].cast("double").alias(c) for k, c in enumerate(names)]), 0.0
    else:
        states, centre = run_factors(cells, Factors(rank, rounds, centre=cells.mean)).df, cells.mean
    return states.select("id", F.array(*names).alias("factors")), cells.errors(states, centre)


def rating_cells(ratings: DataFrame) -> RatingCells:
    return RatingCells(ratings.withColumn("item", F.col("item") + ITEM_OFFSET))
