"""Connected components by alternating star contraction, for link graphs of any diameter."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, functions as F

from tidegraph.runtime import Scratch, materialize


def _hang_on_minimum(links: DataFrame, only_larger: bool, held: list[Scratch]) -> DataFrame:
    """Re-hang the neighbours of each vertex on the smallest vertex it sees.

    ``only_larger``: of the neighbours, only those larger than the vertex move (contraction upwards); otherwise the
    vertex and its smaller neighbours move (contraction downwards). The minimum combines in each task before the shuffle
    and is written, so that it joins back as a plain unique side and the adaptive skew join can split a hub's links.
    """
    held.append(materialize(links.groupBy("a").agg(F.min("b").alias("m")), "least"))
    least = held[-1].df
    if only_larger:
        return (
            links.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.least("m", "a").alias("b")).where("a <> b")
        )
    moved = links.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(least.select("a", F.col("m").alias("b"))).where("a <> b")


def star_components(links: DataFrame, max_rounds: int = 200) -> DataFrame:
    """``links(a, b)`` of longs -> ``(id, component)`` for every linked vertex; component = its smallest reachable id.

    Null ends and self links are ignored. An empty input gives an empty result. Each round is written to the scratch
    folder; only a row count and a checksum reach the driver.
    """
    both = links.where("a is not null and b is not null and a <> b").select(F.col("a").cast("long"), F.col("b").cast("long"))
    current = materialize(both.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    before = None
    for _ in range(max_rounds):
        up = current.df.unionByName(current.df.select(F.col("b").alias("a"), F.col("a").alias("b")))
        held: list[Scratch] = []
        held.append(materialize(_hang_on_minimum(up, True, held).distinct(), "large"))
        down = held[-1].df.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        small = _hang_on_minimum(down, False, held).distinct()
        seen = Observation()
        after = materialize(
            small.observe(seen, F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("s")),
            "links",
        )
        for used in (current, *held):
            used.drop()
        current, state = after, (seen.get["n"], seen.get["s"])
        if state == before or not state[0]:
            break
        before = state
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    stars = current.df
    roots = stars.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct()
    return stars.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(roots)
