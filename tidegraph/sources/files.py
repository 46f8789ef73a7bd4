"""Graph files: edge lists, adjacency lists, Parquet layouts and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

EDGE_SCHEMA = "src long, dst long"


def read_edge_list(spark: SparkSession, path: str, separator: str = "\t", schema: str = EDGE_SCHEMA, comment: str = "#") -> DataFrame:
    """A text edge list under a declared schema; lines that do not fit it are left out."""
    raw = spark.read.csv(path, sep=separator, schema=f"{schema}, _bad string", comment=comment, mode="PERMISSIVE", columnNameOfCorruptRecord="_bad")
    return raw.where("_bad is null and src is not null and dst is not null").drop("_bad")


def write_edge_list(edges: DataFrame, path: str, separator: str = "\t") -> None:
    edges.write.mode("overwrite").csv(path, sep=separator)


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """Lines ``id neighbour neighbour ...`` -> edges."""
    parts = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("p")).where("size(p) > 1")
    return parts.select(F.try_element_at("p", F.lit(1)).try_cast("long").alias("src"), F.explode(F.slice("p", F.lit(2), F.size("p"))).alias("d")).select("src", F.col("d").try_cast("long").alias("dst")).where("src is not null and dst is not null")


def write_adjacency(edges: DataFrame, path: str) -> None:
    lists = edges.groupBy("src").agg(F.array_join(F.transform(F.array_sort(F.collect_list("dst")), lambda x: x.cast("string")), " ").alias("d"))
    lists.select(F.concat_ws(" ", F.col("src").cast("string"), "d").alias("value")).write.mode("overwrite").text(path)


def read_json_edges(spark: SparkSession, path: str, schema: str = EDGE_SCHEMA) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_table(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)


def stream_edges(spark: SparkSession, path: str, schema) -> DataFrame:
    """New Parquet files of a folder as a stream."""
    return spark.readStream.schema(schema).parquet(path)
