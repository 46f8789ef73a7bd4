"""Mixing sources to target weights by proportionate-fair scheduling of blocks.

Each source's documents form blocks. Block i of a source of weight w is released at slot floor(i / w) and due at slot
ceil((i + 1) / w), and the earliest deadline among the released blocks takes each slot. All of this is integer arithmetic
on the exact weights, so that a source is never a whole block away from its share, however long the schedule is.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Mapping
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame, Window as W, functions as F

from tidegraph.runtime import materialize

#: Documents of one numbering group of a source; bounds what is sorted together.
GROUP_ROWS = 4096
#: Slots of a schedule at most, unless another number is given; blocks get larger with the corpus, so that the driver's work stays bounded.
SLOTS = 1_000_000
#: Blocks of a source whose slots go in one row of the broadcast schedule.
CHUNK = 256


def plan(blocks: Mapping[str, int], weights: Mapping[str, float]) -> dict[str, np.ndarray]:
    """The slots of each source's blocks, in their order.

    A phase ends when a source has no block left; the others then share by their weights among themselves, so no block is
    dropped or repeated. In each phase every source is less than one block away from its weight's share at every slot.
    ``weights`` are positive and count as the exact fractions that they are; sources without one or with none count as 1.
    """
    exact = {s: Fraction(weights.get(s) or 1) for s in blocks}
    unit = math.lcm(*(w.denominator for w in exact.values()))
    share = {s: int(w * unit) for s, w in exact.items()}
    left = {s: n for s, n in blocks.items() if n > 0}
    whole = sum(share[s] for s in left)
    taken: dict[str, list[int]] = {s: [] for s in blocks}
    start = 0
    while left:
        waiting = [(0, s, 0) for s in sorted(left)]
        ready: list[tuple[int, str, int]] = []
        slot, done = 0, None
        while done is None:
            while waiting and waiting[0][0] <= slot:
                _, s, i = heapq.heappop(waiting)
                heapq.heappush(ready, (-(-(i + 1) * whole // share[s]), s, i))
            _, s, i = heapq.heappop(ready)
            taken[s].append(start + slot)
            heapq.heappush(waiting, ((i + 1) * whole // share[s], s, i + 1))
            slot += 1
            left[s] -= 1
            done = s if not left[s] else None
        del left[done]
        whole -= share[done]
        start += slot
    return {s: np.array(x, dtype=np.int64) for s, x in taken.items()}


def scheduled(
    docs: DataFrame, weights: Mapping[str, float] | None = None, block_rows: int = 64, power: float = 0.5, slots: int = SLOTS, id_col: str = "doc_id", source_col: str = "source"
) -> DataFrame:
    """``docs`` with ``block, slot, row_in_block``: the mixed order is by (slot, row_in_block).

    ``weights``: target weight by source; without it a source's weight is its document count to the power ``power``. In
    every prefix of slots in which all sources still have blocks, each source is less than one block away from its share.
    A block has ``block_rows`` rows, or as many more as keep the schedule within ``slots`` slots and one for each source.
    A null source counts as the source named by the empty text. Documents of a source are numbered in an order given by a
    hash of their id; repeated ids keep all their rows, in any order. Input columns named like the added ones are replaced. An
    empty table gives an empty result.
    """
    docs = docs.drop("block", "slot", "row_in_block")
    source = F.coalesce(F.col(source_col), F.lit(""))
    order = F.xxhash64(F.col(id_col))
    totals = docs.groupBy(source.alias("_s")).agg(F.count(F.lit(1)).alias("_n"))
    counts = {r["_s"]: r["_n"] for r in totals.collect()}  # one row for each source
    if weights is None:
        weights = {s: n**power for s, n in counts.items()}
    block_rows = max(block_rows, -(-sum(counts.values()) // slots))
    taken = plan({s: -(-n // block_rows) for s, n in counts.items()}, weights)
    spark = docs.sparkSession
    groups = F.broadcast(spark.createDataFrame([(s, -(-n // GROUP_ROWS)) for s, n in counts.items()], "_s string, _groups int"))
    chunks = [(s, k, x[at : at + CHUNK].tolist()) for s, x in taken.items() for k, at in enumerate(range(0, len(x), CHUNK))]
    schedule = F.broadcast(spark.createDataFrame(chunks, "_s string, _chunk long, _slots array<long>"))  # ``slots`` longs at most

    dealt = docs.withColumn("_s", source).join(groups, "_s").withColumn("_g", F.pmod(order, F.col("_groups")).cast("int"))
    sizes = materialize(dealt.groupBy("_s", "_g").agg(F.count(F.lit(1)).alias("_n")), "groups")
    before = sizes.df.withColumn("_before", F.sum("_n").over(W.partitionBy("_s").orderBy("_g").rowsBetween(W.unboundedPreceding, -1)))
    numbered = (
        dealt.withColumn("_rank", F.row_number().over(W.partitionBy("_s", "_g").orderBy(order, F.col(id_col))))
        .join(before.select("_s", "_g", F.coalesce("_before", F.lit(0)).alias("_before")), ["_s", "_g"])
        .withColumn("_row", F.col("_before") + F.col("_rank") - 1)
        .withColumn("block", F.floor(F.col("_row") / block_rows))
        .withColumn("row_in_block", F.col("_row") % block_rows)
        .withColumn("_chunk", F.floor(F.col("block") / CHUNK))
    )
    placed = numbered.join(schedule, ["_s", "_chunk"]).withColumn("slot", F.element_at("_slots", (F.col("block") % CHUNK + 1).cast("int")))
    return placed.select(*docs.columns, "block", "slot", "row_in_block")


def in_mixed_order(mixed: DataFrame) -> DataFrame:
    """Rows in slot order over ranges of slots, for a writer that keeps the order of partitions."""
    return mixed.repartitionByRange("slot", "row_in_block").sortWithinPartitions("slot", "row_in_block")
