"""Message expressions and combiners of users as vectorised functions."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, functions as F


def message_udf(f: Callable[[pd.Series, pd.Series], pd.Series], result: str = "double"):
    """A column function of (value, weight) from a function on series."""

    @F.pandas_udf(result)
    def run(value: pd.Series, weight: pd.Series) -> pd.Series:
        return f(value, weight)

    return run


def combine_udaf(f: Callable[[pd.Series], float], result: str = "double"):
    """An aggregate over a target's messages from a function on a series; for combiners Spark has no aggregate for."""

    @F.pandas_udf(result)
    def run(messages: pd.Series) -> float:
        return f(messages)

    return run


def gather(values: DataFrame, edges: DataFrame, message, combine) -> DataFrame:
    """``(id, value)``: messages along ``edges(src, dst, w)`` from ``values(id, value)``, combined by target."""
    sent = edges.join(values.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), message(F.col("value"), F.col("w")).alias("m"))
    return sent.groupBy("id").agg(combine(sent["m"]).alias("value"))
