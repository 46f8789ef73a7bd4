"""Pairs of items that share a basket, made and told apart as arrays: no pair is a row before it is written."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from tidegraph.operators.blocks import BINS, DEAL_ROWS, Bins, _by, _joined, _ordered, _packed, _ragged, _slices
from tidegraph.runtime import materialize, ship

#: Lines whose lesser items fall into one cell, in which equal pairs meet.
CELL_LINES = 250_000


def item_pairs(lines: DataFrame) -> DataFrame | None:
    """``(src, dst)`` with src < dst, each pair once and written, of ``lines(basket, item)`` in whole numbers; None without lines.

    Lines move once, to their basket; pairs move once, packed, to the cell of their lesser item. Cells are ranges of items of
    about as many lines each; an item with more lines than that is split by the other end.
    """
    spark = lines.sparkSession
    ship(spark)
    lines = lines.where("basket is not null and item is not null").select(F.col("basket").cast("long").alias("basket"), F.col("item").cast("long").alias("item"))
    found = lines.agg(F.min("item").alias("low"), F.max("item").alias("high")).first()
    if found["low"] is None:
        return None
    low, high = found["low"], found["high"]
    bins, n = Bins(low, high), np.zeros(BINS, dtype=np.int64)
    for row in lines.groupBy(bins.column(F.col("item")).alias("bin")).agg(F.count(F.lit(1)).alias("n")).collect():  # a row for each bin
        n[row["bin"]] = row["n"]
    cell, parts = (np.cumsum(n) - n) // CELL_LINES, np.maximum(1, -(-n // CELL_LINES))
    most = int(parts.max())

    def pair_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def chunks(basket, item):
            basket, item = _ordered(basket, item, distinct=True)
            ends = np.append(np.flatnonzero(basket[1:] != basket[:-1]) + 1, len(basket))
            later = np.repeat(ends, np.diff(ends, prepend=0)) - np.arange(len(basket)) - 1
            for lo, hi in _slices(later):
                row, place = _ragged(later[lo:hi])
                if not len(row):
                    continue
                src, dst = _ordered(item[lo + row], item[lo + row + 1 + place], distinct=True)
                bin = bins.of(src)
                task = cell[bin] * most + np.mod(dst, parts[bin])
                order = _by(task)
                src, dst, task = src[order], dst[order], task[order]
                starts = np.flatnonzero(np.diff(task, prepend=-1))
                ends_ = np.append(starts[1:], len(task))
                out = [task[starts].tolist(), *([_packed(x[a:z]) for a, z in zip(starts, ends_)] for x in (src, dst))]
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, (pa.int64(), pa.binary(), pa.binary()))], ["task", "one", "two"])

        held, rows = [], 0
        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= DEAL_ROWS:
                basket, item = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in (0, 1))
                whole = int(np.searchsorted(basket, basket[-1]))  # the last basket may go on
                if whole:
                    yield from chunks(basket[:whole], item[:whole])
                held = [pa.RecordBatch.from_arrays([pa.array(basket[whole:]), pa.array(item[whole:])], ["basket", "item"])]
                rows = len(basket) - whole if whole else 0
        if held:
            yield from chunks(*(np.concatenate([b.column(k).to_numpy() for b in held]) for k in (0, 1)))

    def merge(table: pa.Table) -> pa.Table:
        src, dst = _ordered(*(_joined(table[c]) for c in ("one", "two")), distinct=True)
        return pa.table({"src": src, "dst": dst})

    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(int(cell.max()) + 1, 1_000))
    packed = lines.repartition("basket").sortWithinPartitions("basket").mapInArrow(pair_up, "task long, one binary, two binary")
    return materialize(packed.repartition(tasks, "task").groupBy("task").applyInArrow(merge, "src long, dst long"), "pairs", "zstd", free=True).df
