"""Switches of the physical planner, set for the length of a block: sideways filters, cost-based order, one-pass aggregates."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import SparkSession


@contextmanager
def settings(spark: SparkSession, **values) -> Iterator[None]:
    """Session settings (dots as double underscores) that go back to what they were."""
    names = {k.replace("__", "."): str(v) for k, v in values.items()}
    before = {k: spark.conf.get(k, None) for k in names}
    try:
        for k, v in names.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def bloom_filters(spark: SparkSession):
    """Runtime bloom filters from the small side of a join at the scan of the large one, whatever the scan's size."""
    return settings(spark, spark__sql__optimizer__runtime__bloomFilter__enabled="true", spark__sql__optimizer__runtime__bloomFilter__applicationSideScanSizeThreshold="0", spark__sql__autoBroadcastJoinThreshold="-1")


def one_pass_aggregates(spark: SparkSession):
    """Sort aggregates after merge joins on the same key."""
    return settings(spark, spark__sql__execution__replaceHashWithSortAgg="true")


def cost_based(spark: SparkSession):
    """Join order from table statistics; see ``analyse``."""
    return settings(spark, spark__sql__cbo__enabled="true", spark__sql__cbo__joinReorder__enabled="true", spark__sql__cbo__planStats__enabled="true")


def analyse(spark: SparkSession, *tables: str) -> None:
    for t in tables:
        spark.sql(f"ANALYZE TABLE {t} COMPUTE STATISTICS FOR ALL COLUMNS")
