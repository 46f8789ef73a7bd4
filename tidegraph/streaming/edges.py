"""Edges as a stream: windowed counts, and results kept up to date as edges arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from tidegraph.operators.components import star_components
from tidegraph.runtime import Scratch, materialize


def timed(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events with a time stamp that carries a watermark; naive time stamps count as UTC."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def tumbling(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """``(start, event_type, n, value)`` by window; ``slide`` makes the windows overlap."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("value")).select(F.col("w.start").alias("start"), "event_type", "n", "value")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """``(start, finish, user_id, n)`` by user session."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "user_id", "n")


class ComponentKeeper:
    """Components under arriving edges: each micro-batch is contracted together with the links of the components so far.

    Edges are only added, so labels only fall and what was found stays true; a deletion needs a run from all edges. Use
    ``process`` with ``foreachBatch``; a batch that is delivered again changes nothing.
    """

    def __init__(self):
        self.links: Scratch | None = None
        self.done: set[int] = set()

    def process(self, batch: DataFrame, number: int) -> None:
        if number in self.done:
            return
        fresh = batch.select(F.col("src").alias("a"), F.col("dst").alias("b"))
        known = fresh if self.links is None else fresh.unionByName(self.links.df.select(F.col("id").alias("a"), F.col("component").alias("b")))
        after = materialize(star_components(known), "components")
        if self.links is not None:
            self.links.drop()
        self.links = after
        self.done.add(number)

    def components(self) -> DataFrame | None:
        return self.links.df if self.links else None


class DistanceKeeper:
    """Hop distances from a source under arriving edges: new edges that shorten a path start a frontier of their own."""

    def __init__(self, vertices: DataFrame, source):
        from tidegraph.plans.iterate import VertexState

        self.state = VertexState(vertices.select("id", F.when(F.col("id") == F.lit(source), 0).cast("bigint").alias("value")), "replace")
        self.edges: Scratch | None = None

    def process(self, batch: DataFrame, number: int) -> None:
        from tidegraph.plans.iterate import counted

        fresh = batch.select("src", "dst")
        after = materialize(fresh if self.edges is None else self.edges.df.unionByName(fresh), "edges")
        if self.edges is not None:
            self.edges.drop()
        self.edges = after
        own, frontier = fresh, self.state.current().where("value is not null")
        while True:
            current = self.state.current()
            least = own.join(frontier.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg((F.min("value") + 1).alias("new"))
            delta, n = counted(current.join(least, "id").where("value is null or new < value").select("id", F.col("new").alias("value")), "delta")
            if not n:
                return
            self.state.apply(delta, n)
            own, frontier = self.edges.df, delta.df


def run_available(stream: DataFrame, process, checkpoint: str) -> None:
    """Feeds all that is available to ``process(batch, number)``, then stops."""
    query = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", checkpoint).foreachBatch(process).start()
    query.awaitTermination()


def deduplicated(events: DataFrame, keys: list[str]) -> DataFrame:
    """The first of events with equal keys within the watermark."""
    return events.dropDuplicatesWithinWatermark(keys)


def with_vertices(edges: DataFrame, vertices: DataFrame, end: str = "src") -> DataFrame:
    """Streamed edges with the attributes of a static vertex table at one end."""
    return edges.join(vertices.withColumnRenamed("id", end), end)


def running_degrees(edges: DataFrame) -> DataFrame:
    """``(id, degree)``: the out-degree so far of every vertex that a micro-batch touches, from state kept by vertex."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def count(key, frames, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"id": [key[0]], "degree": [n]})

    return edges.select(F.col("src").alias("id"), "dst").groupBy("id").applyInPandasWithState(count, "id long, degree long", "n long", "update", GroupStateTimeout.NoTimeout)
