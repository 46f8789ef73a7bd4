"""Rating graphs as cells of packed arrays: a superstep sends a cell the factors of each vertex it holds once, not once for each edge."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, functions as F

from tidegraph.operators.blocks import BINS, DEAL_ROWS, Bins
from tidegraph.runtime import Scratch, materialize, ship
from tidegraph.vertexprog.api import Factors

#: Ratings of a cell, which a task holds; those that are looked at at once.
CELL_RATINGS, AT_ONCE = 1_000_000, 200_000


def _zip(x: np.ndarray) -> bytes:
    return len(x).to_bytes(8, "little") + pa.Codec("zstd", compression_level=1).compress(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T.tobytes(), asbytes=True)


def _unzip(x: bytes, kind: str) -> np.ndarray:
    size, n = np.dtype(kind).itemsize, int.from_bytes(x[:8], "little")
    planes = np.frombuffer(pa.Codec("zstd").decompress(x[8:], size * n), dtype=np.uint8).reshape(size, n)
    return np.ascontiguousarray(planes.T).view(kind).ravel()


class RatingCells:
    """``ratings(user, item, rating)`` in whole-number ids, dealt out once to cells that are ranges of users; ratings without an end or a value are left out.

    A cell is one row: the ids it holds, and for each rating its ends as places among them. A range of users with more ratings
    than a cell may hold is split by item. ``wanted`` has ``(cell, id)`` of what each cell holds.
    """

    def __init__(self, ratings: DataFrame):
        spark = ratings.sparkSession
        ship(spark)
        ends = ratings.select(F.col("user").cast("long").alias("user"), F.col("item").cast("long").alias("item"), F.col("rating").cast("double").alias("rating")).where("user is not null and item is not null and rating is not null")
        found = ends.agg(F.min("user").alias("low"), F.max("user").alias("high"), F.avg("rating").alias("mean")).first()
        self.mean = found["mean"] or 0.0
        bins, n = Bins(found["low"] or 0, found["high"] or 0), np.zeros(BINS, dtype=np.int64)
        for row in ends.groupBy(bins.column(F.col("user")).alias("bin")).agg(F.count(F.lit(1)).alias("n")).collect():  # a row for each bin
            n[row["bin"]] = row["n"]
        cell, parts = (np.cumsum(n) - n) // CELL_RATINGS, np.maximum(1, -(-n // CELL_RATINGS))
        most = int(parts.max())
        self.parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(int(cell.max()) + 1, 1_000))

        def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            def chunk(held):
                user, item, rating = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in range(3))
                at = bins.of(user)
                task = cell[at] * most + np.mod(item, parts[at])
                order = np.argsort(task, kind="stable")
                starts = np.flatnonzero(np.diff(task[order], prepend=-1))
                out = [task[order][starts].tolist(), *([_zip(x[order][a:z]) for a, z in zip(starts, np.append(starts[1:], len(task)))] for x in (user, item, rating))]
                return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, (pa.int64(), pa.binary(), pa.binary(), pa.binary()))], ["cell", "user", "item", "rating"])

            held, rows = [], 0
            for batch in batches:
                held.append(batch)
                rows += batch.num_rows
                if rows >= DEAL_ROWS:
                    yield chunk(held)
                    held, rows = [], 0
            if rows:
                yield chunk(held)

        def pack(table: pa.Table) -> pa.Table:
            user, item, rating = (np.concatenate([_unzip(x.as_py(), kind) for x in table[c]]) for c, kind in (("user", "<i8"), ("item", "<i8"), ("rating", "<f8")))
            order = np.lexsort((item, user))
            ids, at = np.unique(np.concatenate([user[order], item[order]]), return_inverse=True)
            at = at.astype("<i4")
            return pa.table({"cell": [table["cell"][0].as_py()], "ids": [_zip(ids)], "one": [_zip(at[: len(user)])], "two": [_zip(at[len(user) :])], "rating": [_zip(rating[order])]})

        def held_ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for cell, packed in zip(batch["cell"].to_pylist(), batch["ids"].to_pylist()):
                    ids = _unzip(packed, "<i8")
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), cell)), pa.array(ids)], ["cell", "id"])

        dealt = ends.mapInArrow(deal, "cell long, user binary, item binary, rating binary").repartition(self.parts, "cell")
        self.written: Scratch = materialize(dealt.groupBy("cell").applyInArrow(pack, "cell long, ids binary, one binary, two binary, rating binary"), "cells", free=True)
        self.kept = self.written.df.repartition(self.parts, "cell").persist(StorageLevel.MEMORY_AND_DISK)
        self.wanted: Scratch = materialize(self.written.df.select("cell", "ids").mapInArrow(held_ids, "cell long, id long"), "wanted", "zstd")

    def each(self, states: DataFrame, run, schema: str) -> DataFrame:
        """``run(one, two, rating, ids, factors)`` of every cell, of the ratings of which both ends have a row in ``states(id, f0, f1, ...)``."""
        names = [c for c in states.columns if c != "id"]

        def meet(cells: pa.Table, sent: pa.Table) -> pa.Table:
            if not len(cells) or not len(sent):
                return run(np.zeros(0, np.int32), np.zeros(0, np.int32), np.zeros(0), np.zeros(0, np.int64), np.zeros((0, len(names))))
            ids, one, two, rating = (_unzip(cells[c][0].as_py(), kind) for c, kind in (("ids", "<i8"), ("one", "<i4"), ("two", "<i4"), ("rating", "<f8")))
            place = np.searchsorted(ids, sent["id"].to_numpy())
            there, factors = np.zeros(len(ids), dtype=bool), np.zeros((len(ids), len(names)))
            there[place] = True
            for k, c in enumerate(names):
                factors[place, k] = sent[c].to_numpy()
            if not there.all():
                both = there[one] & there[two]
                one, two, rating = one[both], two[both], rating[both]
            return run(one, two, rating, ids, factors)

        dealt = self.wanted.df.join(states, "id").select("cell", "id", *names)
        return self.kept.groupBy("cell").cogroup(dealt.groupBy("cell")).applyInArrow(meet, schema)

    def errors(self, states: DataFrame, centre: float) -> DataFrame:
        """One row ``rmse, rmse_mean``: the error of ``centre`` and the product of factors, and that of the mean."""
        mean = self.mean

        def sums(one, two, rating, ids, factors) -> pa.Table:
            missed = sum(float(((rating[s] - centre - (factors[one[s]] * factors[two[s]]).sum(1)) ** 2).sum()) for s in _cuts(len(one)))
            return pa.table({"n": [len(one)], "missed": [missed], "off": [float((rating - mean).sum())], "square": [float(((rating - mean) ** 2).sum())]})

        total = self.each(states, sums, "n long, missed double, off double, square double").agg(*[F.sum(c).alias(c) for c in ("n", "missed", "off", "square")])
        n = F.nullif("n", F.lit(0))
        return total.select(F.sqrt(F.col("missed") / n).alias("rmse"), F.sqrt(F.greatest(F.col("square") / n - F.pow(F.col("off") / n, F.lit(2.0)), F.lit(0.0))).alias("rmse_mean"))

    def drop(self) -> None:
        self.kept.unpersist()
        self.written.drop()
        self.wanted.drop()


def _cuts(n: int) -> list[slice]:
    return [slice(k, k + AT_ONCE) for k in range(0, n, AT_ONCE)]


def run_factors(cells: RatingCells, program: Factors) -> Scratch:
    """``(id, f0, f1, ...)`` after the program's rounds: what its messages do to their receivers, summed by cell, then by vertex."""
    rank, centre = program.rank, program.centre
    names = [f"f{k}" for k in range(rank)]
    row = f"id long, {', '.join(f'{c} double' for c in names)}"

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            states = np.array([program.init(v) for v in batch["id"].to_pylist()]).reshape(batch.num_rows, rank)
            yield pa.RecordBatch.from_arrays([batch["id"], *[pa.array(states[:, k]) for k in range(rank)]], ["id", *names])

    def pulls(one, two, rating, ids, factors) -> pa.Table:
        total = np.zeros((rank, len(ids)))
        for s in _cuts(len(one)):
            x, y = factors[one[s]], factors[two[s]]
            error = (rating[s] - centre - (x * y).sum(1))[:, None]
            for ends, pull in ((one[s], error * y), (two[s], error * x)):
                for k in range(rank):
                    total[k] += np.bincount(ends, weights=pull[:, k], minlength=len(ids))
        n = np.bincount(one, minlength=len(ids)) + np.bincount(two, minlength=len(ids))
        return pa.table({"id": ids, "n": n.astype(np.int64), **dict(zip(names, total))})

    states = materialize(cells.wanted.df.select("id").distinct().mapInArrow(first, row), "factors", free=True)
    for _ in range(program.rounds):
        sums = cells.each(states.df, pulls, f"id long, n long, {', '.join(f'{c} double' for c in names)}").groupBy("id").agg(F.sum("n").alias("n"), *[F.sum(c).alias(f"g{c}") for c in names])
        step = F.lit(program.rate) / F.greatest(F.lit(1.0), F.sqrt("n"))
        moved = [(F.col(c) + step * F.greatest(F.lit(-50.0), F.least(F.lit(50.0), F.col(f"g{c}") - program.shrink * F.col("n") * F.col(c)))).alias(c) for c in names]
        before, states = states, materialize(states.df.join(sums, "id").select("id", *moved), "factors", free=True)
        before.drop()
    return states
