"""Relational steps around graph analyses: histograms, joining results, rehydration, as-of and range joins, metadata."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F


def histogram(df: DataFrame, column: str, bins: int = 20) -> DataFrame:
    """``(bucket, lo, hi, n)`` over equal bins of [min, max]; empty bins stay, nulls do not count, one value fills the first bin."""
    c = F.col(column).cast("double")
    ends = df.agg(F.min(c).alias("a"), F.max(c).alias("b")).where("a is not null")
    place = F.when(F.col("b") > F.col("a"), F.least(F.floor((c - F.col("a")) / (F.col("b") - F.col("a")) * bins), F.lit(bins - 1))).otherwise(0)
    counts = df.where(F.col(column).isNotNull()).crossJoin(F.broadcast(ends)).groupBy(place.cast("int").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))  # ends: one row
    every = ends.select("a", "b", F.explode(F.sequence(F.lit(0), F.lit(bins - 1))).alias("bucket"))
    edge = lambda k: F.col("a") + (F.col("b") - F.col("a")) * k / bins
    return every.join(counts, "bucket", "left").select("bucket", edge(F.col("bucket")).alias("lo"), edge(F.col("bucket") + 1).alias("hi"), F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def near_or_important(rank: DataFrame, dist: DataFrame, max_dist, min_rank: Column | float) -> DataFrame:
    """``(id, dist, rank)`` of vertices within ``max_dist`` or of rank above ``min_rank``."""
    return dist.join(rank, "id", "full").where((F.col("dist") <= max_dist) | (F.col("rank") > min_rank)).select("id", "dist", "rank")


def rehydrate(ids: DataFrame, vertices: DataFrame, *columns: str) -> DataFrame:
    """Attributes joined back to a result that was computed on ids alone."""
    return ids.join(vertices.select("id", *columns), "id")


def profile(edges: DataFrame, **conditions: str) -> DataFrame:
    """One row: how many rows satisfy each named condition, from one scan."""
    return edges.agg(*[F.count_if(F.expr(c)).alias(name) for name, c in conditions.items()])


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """``left`` with the last ``value`` of ``right`` at or before its time for the same key; one sort, no join."""
    rows = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1)).unionByName(
        right.select(key, at, F.col(value).alias("_v"), F.lit(0).alias("_side")), allowMissingColumns=True
    )
    latest = F.last("_v", ignorenulls=True).over(W.partitionBy(key).orderBy(at, "_side").rowsBetween(W.unboundedPreceding, 0))
    return rows.withColumn(f"last_{value}", latest).where("_side = 1").drop("_v", "_side")


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Points in [low, high): an equality join on cells of ``width`` with the bounds as residual. Ranges should span few cells."""
    cell = lambda c: F.floor(F.col(c) / width)
    spread = ranges.withColumn("_cell", F.explode(F.sequence(cell(low), cell(high))))
    return points.withColumn("_cell", cell(point)).join(spread, "_cell").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_cell")


# The multipliers and modulus of the attribute generator; products of ids below 2^31 stay within 64 bits.
_PRIME = 2_147_483_647
_STEPS = (1_103_515_245, 1_140_671_485, 1_664_525, 22_695_477)


def hashed(identifier: Column, number: int) -> Column:
    """A value in [0, 2^31 - 1) from an id and a column number, by integer arithmetic that any SQL engine repeats."""
    a = _STEPS[number % 4] % _PRIME
    b = (number * 97_003 + 12_345) % _PRIME
    once = ((identifier % _PRIME) * a + b) % _PRIME
    return (once * 48_271 + number) % _PRIME


def hashed_sql(identifier: str, number: int) -> str:
    a, b = _STEPS[number % 4] % _PRIME, (number * 97_003 + 12_345) % _PRIME
    return f"((((({identifier}) % {_PRIME}) * {a} + {b}) % {_PRIME}) * 48271 + {number}) % {_PRIME}"


def attribute_plan() -> list[tuple[str, str, float]]:
    """(column, kind, parameter) of the synthetic vertex attributes: 24 uniform, 8 zipf-like, 18 real and 10 text columns."""
    uniform = [(f"attr_u{k:02d}", "u", max(2, round(2 * (5e8) ** (k / 23)))) for k in range(24)]
    zipf = [(f"attr_z{k + 1}", "z", round(1.1 + 0.2 * k, 1)) for k in range(8)]
    real = [(f"attr_f{k + 1:02d}", "f", float(10 ** (k // 2))) for k in range(18)]
    text = [(f"attr_s{k + 1:02d}", "s", 10 ** (1 + k // 2)) for k in range(10)]
    return [*uniform, *zipf, *real, *text]


def with_metadata(vertices: DataFrame) -> DataFrame:
    """``vertices`` with the synthetic attributes of ``attribute_plan``; ids must be longs."""
    columns = {}
    for number, (name, kind, p) in enumerate(attribute_plan()):
        h = hashed(F.col("id"), number)
        if kind == "u":
            columns[name] = h % int(p)
        elif kind == "z":
            columns[name] = F.floor(F.pow((h + 1) / F.lit(float(_PRIME)), F.lit(-1.0 / p))).cast("long")
        elif kind == "f":
            columns[name] = h / F.lit(float(_PRIME)) * F.lit(p)
        else:
            columns[name] = F.concat(F.lit(f"{name}_"), F.lpad((h % int(p)).cast("string"), 4 + number - 50, "0"))
    return vertices.withColumns(columns)


def metadata_sql(source: str) -> str:
    """The same attributes in SQL over a relation with a bigint ``id``."""
    parts = []
    for number, (name, kind, p) in enumerate(attribute_plan()):
        h = f"({hashed_sql('id', number)})"
        if kind == "u":
            parts.append(f"{h} % {int(p)} AS {name}")
        elif kind == "z":
            parts.append(f"CAST(floor(pow(({h} + 1) / CAST({_PRIME} AS DOUBLE), {-1.0 / p!r})) AS BIGINT) AS {name}")
        elif kind == "f":
            parts.append(f"{h} / CAST({_PRIME} AS DOUBLE) * CAST({p!r} AS DOUBLE) AS {name}")
        else:
            parts.append(f"'{name}_' || lpad(CAST({h} % {int(p)} AS VARCHAR), {4 + number - 50}, '0') AS {name}")
    return f"SELECT id, {', '.join(parts)} FROM {source}"
