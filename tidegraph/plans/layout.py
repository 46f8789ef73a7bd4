"""Physical layouts of edges: two copies, each bucketed and sorted by one end; grids; sizes."""

from __future__ import annotations

import math

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, SparkSession, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.runtime import Scratch, materialize

#: Rows up to which a frontier, an overlay or a list of hubs of a counted size is sent to every executor.
BROADCAST_ROWS = 200_000
#: Edges of one source that stay together; those of a larger source are dealt out over several partitions.
HUB_EDGES = 1_000_000
#: Edges of a partition: fewer than the first are not worth a task, more than the second are too many for one.
FEW_EDGES, MANY_EDGES = 100_000, 5_000_000


def counted(df: DataFrame, label: str) -> tuple[Scratch, int]:
    """Write ``df`` and return it with its row count, from one job."""
    seen = Observation()
    written = materialize(df.observe(seen, F.count(F.lit(1)).alias("n")), label)
    return written, seen.get["n"]


def sized(df: DataFrame, rows: int) -> DataFrame:
    """A broadcast hint if ``rows``, counted before, allow it."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def parts_for(edges: int, wanted: int) -> int:
    """Partitions for so many edges: ``wanted``, unless these would be tiny or huge."""
    return max(1, min(wanted, -(-edges // FEW_EDGES)), -(-edges // MANY_EDGES))


class DealtEdges:
    """``edges(src, dst, ...)`` written once, dealt out by source and kept, so that a round moves only what meets them.

    Sources with over HUB_EDGES edges, of which there is at most one in so many edges, are split by a salt from the target;
    rows that meet them are copied to each of their parts. A lost executor reads the written edges again, however long
    their derivation was. ``kept=False`` takes edges as they lie, for copies that are bucketed by source.
    """

    def __init__(self, edges: DataFrame, kept: bool = True):
        self.hubs, self.written, self.kept = None, None, kept
        if not kept:
            self.df = edges
            return
        self.written, self.rows = counted(edges, "edges")
        dealt, keys = self.written.df, ["src"]
        if self.rows > HUB_EDGES:
            heavy = dealt.groupBy("src").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HUB_EDGES).select("src", F.ceil(F.col("n") / HUB_EDGES).cast("int").alias("parts"))
            hubs, n = counted(heavy, "hubs")
            if n:
                self.hubs = sized(hubs.df, n)
                salt = F.when(F.col("parts").isNull(), 0).otherwise(F.pmod(F.xxhash64("dst"), F.col("parts"))).cast("int")
                dealt, keys = dealt.join(self.hubs, "src", "left").withColumn("salt", salt).drop("parts"), ["src", "salt"]
        wanted = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        self.df = dealt.repartition(parts_for(self.rows, wanted), *keys).persist(StorageLevel.MEMORY_AND_DISK)

    def meet(self, side: DataFrame, scan: DataFrame | None = None) -> DataFrame:
        """The edges (of ``scan``, a part of them, if it is given) joined with ``side(src, ...)`` on their source."""
        scan = self.df if scan is None else scan
        if self.hubs is None:
            return scan.join(side, "src")
        spread = side.join(self.hubs, "src", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
        return scan.join(spread, ["src", "salt"]).drop("salt")

    def unpersist(self) -> None:
        if self.kept:
            self.df.unpersist()


def keyed(df: DataFrame, key: str, partitions: int | None = None) -> DataFrame:
    """``df`` dealt out by ``key`` and kept; later joins and aggregates on the key move only their other side."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, key).persist(StorageLevel.MEMORY_AND_DISK)


def write_bucketed(graph: PropertyGraph, name: str, buckets: int, by: tuple[str, ...] = ("src", "dst"), codec: str = "zstd") -> dict[str, str]:
    """A bucketed and sorted table for each end in ``by`` and for the vertices; joins and aggregates on it need no exchange."""
    out = {}
    for end in by:
        out[end] = f"{name}_by_{end}"
        (graph.edges.repartition(buckets, end).write.mode("overwrite").option("compression", codec).bucketBy(buckets, end).sortBy(end).format("parquet").saveAsTable(out[end]))
    out["id"] = f"{name}_vertices"
    (graph.vertices.repartition(buckets, "id").write.mode("overwrite").option("compression", codec).bucketBy(buckets, "id").sortBy("id").format("parquet").saveAsTable(out["id"]))
    return out


def grid_cell(rows: int, columns: int):
    """The cell of an edge in a two-dimensional hash grid."""
    return (F.pmod(F.xxhash64("src"), F.lit(rows)) * columns + F.pmod(F.xxhash64("dst"), F.lit(columns))).cast("int")


def grid_of(parts: int) -> tuple[int, int]:
    rows = max(d for d in range(1, math.isqrt(parts) + 1) if parts % d == 0)
    return rows, parts // rows


def stored_bytes(spark: SparkSession, path: str) -> int:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(target).getLength()


def table_bytes(spark: SparkSession, name: str) -> int:
    """Bytes of a table's files."""
    rows = spark.sql(f"DESCRIBE FORMATTED {name}").where("col_name = 'Location'").collect()
    return stored_bytes(spark, rows[0]["data_type"])
