"""Triangles and common neighbours over blocks of a graph: edges meet in tasks as arrays, and no wedge is ever a row.

Vertices fall into bins and bins into bands of about BAND_EDGES edges. A task takes two bands (common neighbours) or three
(triangles), so it holds a bounded share of the edges whatever their number, and an edge goes only to tasks whose other
bands have an edge to its bins. Bins are ranges of ids, so graphs whose neighbours have near ids copy few edges; where ids
are too uneven, they are remainders. In the worst case an edge goes to as many tasks as there are bands.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, functions as F

from tidegraph.runtime import materialize, ship

BINS = 1_024
#: Edges of a band, of which a task holds two or three.
BAND_EDGES = 2_000_000
#: Bands of a graph with fewer edges than these would hold.
FEW_BANDS = 4
#: Edges that are dealt out at once, and wedges that are looked at at once.
DEAL_ROWS, WEDGES = 200_000, 1_000_000
_DEALT = "task long, kind int, one binary, two binary"


@dataclass
class Bins:
    """``ranges``: equal ranges from ``low``, else remainders."""

    low: int
    high: int
    ranges: bool = True

    @property
    def width(self) -> int:
        return max(1, -(-(self.high - self.low + 1) // BINS))

    def column(self, id: Column) -> Column:
        return (F.floor((id - self.low) / self.width) if self.ranges else F.pmod(id, F.lit(BINS))).cast("int")

    def of(self, ids: np.ndarray) -> np.ndarray:
        return (ids - self.low) // self.width if self.ranges else np.mod(ids, BINS)


@dataclass
class Bands:
    """How the sources of ``edges`` are banded, and which bands have an edge to which bin of targets."""

    edges: DataFrame
    sources: Bins
    targets: Bins
    band: np.ndarray  # of a bin of sources
    near: np.ndarray  # bins of targets x bands

    @property
    def count(self) -> int:
        return self.near.shape[1]


def is_banded(edges: DataFrame) -> bool:
    """Whether ids are whole numbers."""
    return all(t in ("bigint", "int", "smallint", "tinyint") for c, t in edges.dtypes if c in ("src", "dst"))


def banded(edges: DataFrame, mirrored: bool, halves: bool = False) -> Bands | None:
    """``edges(src, dst)`` written once and banded; None if there are none. ``mirrored``: each also counts from dst to src. ``halves`` are written already."""
    figures = [F.count(F.lit(1)).alias("n"), *[f(c).alias(f"{f.__name__}_{c}") for f in (F.min, F.max) for c in ("src", "dst")]]
    ends = edges.where("src is not null and dst is not null").select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    if halves:
        written, found = ends, ends.agg(*figures).first()
    else:
        seen = Observation()
        written = materialize(ends.observe(seen, *figures), "blocks", "zstd", free=True).df
        found = seen.get
    if not found["n"]:
        return None
    sources, targets = Bins(found["min_src"], found["max_src"]), Bins(found["min_dst"], found["max_dst"])
    if mirrored:
        sources = targets = Bins(min(sources.low, targets.low), max(sources.high, targets.high))
    for ranges in (True, False):
        sources.ranges = ranges
        rows = written.groupBy(sources.column(F.col("src")).alias("s"), targets.column(F.col("dst")).alias("t")).agg(F.count(F.lit(1)).alias("n")).toPandas()
        meet = np.zeros((BINS, BINS), dtype=np.int64)
        meet[rows["s"], rows["t"]] = rows["n"]
        if mirrored:
            meet = meet + meet.T
        size = meet.sum(1)
        if size.max() <= 2 * BAND_EDGES:
            break
    band = (np.cumsum(size) - size) // min(BAND_EDGES, max(size.sum() // FEW_BANDS, FEW_BANDS))
    band = np.unique(band, return_inverse=True)[1]
    near = np.zeros((BINS, band.max() + 1), dtype=bool)
    for b in range(near.shape[1]):
        near[:, b] = meet[band == b].any(0)
    return Bands(written, sources, targets, band, near)


def _ragged(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For lists of these lengths laid end to end: the list of each entry and its place in it."""
    of = np.repeat(np.arange(len(counts)), counts)
    return of, np.arange(len(of)) - np.repeat(np.cumsum(counts) - counts, counts)


def _packed(x: np.ndarray) -> bytes:
    """Differences by as many planes of bytes as they need, which compress well, after their number and that of planes; signs stand in the lowest bit."""
    step = np.diff(x, prepend=0).astype("<i8")
    step = ((step << 1) ^ (step >> 63)).view("<u8")
    planes = (int(step.max()).bit_length() + 7) // 8 if len(step) else 0
    bytes_ = np.ascontiguousarray(step.view(np.uint8).reshape(-1, 8)[:, :planes].T)
    return len(x).to_bytes(8, "little") + bytes([planes]) + pa.Codec("zstd", compression_level=1).compress(bytes_, asbytes=True)


def _unpacked(x: bytes) -> np.ndarray:
    size, planes = int.from_bytes(x[:8], "little"), x[8]
    step = np.zeros((size, 8), dtype=np.uint8)
    if planes:
        step[:, :planes] = np.frombuffer(pa.Codec("zstd").decompress(x[9:], planes * size), dtype=np.uint8).reshape(planes, size).T
    step = step.view("<u8").ravel()
    return np.cumsum((step >> np.uint64(1)).view("<i8") ^ -(step & np.uint64(1)).view("<i8"))


def _joined(column: pa.ChunkedArray) -> np.ndarray:
    """What the packed arrays of a column hold, end to end."""
    column = [x.as_py() for x in column]
    sizes = [int.from_bytes(x[:8], "little") for x in column]
    out, at = np.empty(sum(sizes), dtype=np.int64), 0
    for x, size in zip(column, sizes):
        out[at : at + size] = _unpacked(x)
        at += size
    return out


def _once(x: np.ndarray) -> np.ndarray:
    """Sorted ``x`` without repeats. Sorting and this take a fraction of the time of ``np.unique``, which hashes."""
    return x[np.append(True, x[1:] != x[:-1])] if len(x) else x


def _ordered(one: np.ndarray, two: np.ndarray, distinct: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Whole numbers by (one, two), as single keys where these fit; each pair once if ``distinct``."""
    if not len(one):
        return one, two
    low, least = int(one.min()), int(two.min())
    span = int(two.max()) - least + 1
    if (int(one.max()) - low + 1) * span < 1 << 63:
        key = (one.astype(np.int64) - low) * span + (two.astype(np.int64) - least)
        key.sort()
        if distinct:
            key = _once(key)
        one = key // span
        key -= one * span
        return one + low, key + least
    order = np.lexsort((two, one))
    one, two = one[order], two[order]
    if distinct:
        new = np.append(True, (one[1:] != one[:-1]) | (two[1:] != two[:-1]))
        one, two = one[new], two[new]
    return one, two


def _by(task: np.ndarray) -> np.ndarray:
    """The places of rows by ``task``, 0 or more, those of a task in their order."""
    bits = len(task).bit_length()
    if not len(task) or int(task.max()) >= 1 << (63 - bits):
        return np.argsort(task, kind="stable")
    key = (task.astype(np.int64) << bits) | np.arange(len(task))
    key.sort()
    return key & ((1 << bits) - 1)


def _numbered(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values, ascending, and the place of each of ``x`` among them."""
    low, high = (int(x.min()), int(x.max())) if len(x) else (0, 0)
    if high - low < max(4 * len(x), 1 << 20):
        seen = np.zeros(high - low + 1, dtype=bool)
        at = x - low
        seen[at] = True
        return np.flatnonzero(seen) + low, (np.cumsum(seen, dtype=np.int32) - np.int32(1))[at]
    ids = _once(np.sort(x))
    return ids, np.searchsorted(ids, x).astype(np.int32)


def _dealt(df: DataFrame, deal: Callable, kind: int, mirrored: bool = False) -> DataFrame:
    """``df`` of two columns as packed arrays by task. ``deal(one, two)`` gives the rows' numbers, ascending, and their tasks. ``mirrored``: rows also the other way round."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def chunk(held):
            one, two = (np.concatenate([b.column(k).to_numpy(zero_copy_only=False) for b in held]) for k in (0, 1))
            if mirrored:
                one, two = np.concatenate([one, two]), np.concatenate([two, one])
            if two.dtype.kind == "i":
                one, two = _ordered(one, two)
            else:
                order = np.lexsort((two, one))
                one, two = one[order], two[order]
            row, task = deal(one, two)
            order = _by(task)
            row, task = row[order], task[order]
            starts = np.flatnonzero(np.diff(task, prepend=-1))
            ends = np.append(starts[1:], len(task))
            second = _packed if two.dtype.kind == "i" else np.ndarray.tobytes
            out = [[int(task[a]) for a in starts], [kind] * len(starts), [_packed(one[row[a:z]]) for a, z in zip(starts, ends)], [second(two[row[a:z]]) for a, z in zip(starts, ends)]]
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, (pa.int64(), pa.int32(), pa.binary(), pa.binary()))], ["task", "kind", "one", "two"])

        held, rows = [], 0
        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= DEAL_ROWS:
                yield chunk(held)
                held, rows = [], 0
        if rows:
            yield chunk(held)

    return df.mapInArrow(run, _DEALT)


def _lists(key: np.ndarray, n: int) -> np.ndarray:
    """Where the list of each of ``n`` keys starts among sorted ``key``; one more for the end."""
    return np.searchsorted(key, np.arange(n + 1, dtype=key.dtype)).astype(np.int32)


def _slices(work: np.ndarray, most: int = WEDGES) -> Iterator[tuple[int, int]]:
    """Runs of entries with about so much work each."""
    total, at = np.cumsum(work), 0
    while at < len(work):
        done = total[at - 1] if at else 0
        end = max(at + 1, int(np.searchsorted(total, done + most, "right")))
        yield at, end
        at = end


# Triangles


def triangle_counts(edges: DataFrame, orient: str = "degree", halves: bool = False) -> tuple[DataFrame, DataFrame] | None:
    """``(id, triangles)`` of every vertex in a triangle, over undirected ``edges`` that may repeat, and the edges as written; None without edges.

    ``orient``: inside a band each edge leads up by id, or by (degree, id) so that no vertex keeps many out-edges. ``halves``: ``edges``
    are those of ``PropertyGraph.halves``.
    """
    ship(edges.sparkSession)
    plan = banded(edges if halves else edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")), True, halves)
    if plan is None:
        return None
    bins, band, near, p = plan.sources, plan.band, plan.near, plan.count

    def deal(src, dst):
        s, d = bins.of(src), bins.of(dst)
        both = near[s] & near[d]
        row, third = np.nonzero(both)
        one, two = band[s][row], band[d][row]
        least, most = np.minimum(np.minimum(one, two), third), np.maximum(np.maximum(one, two), third)
        return row, (least * p + (one + two + third - least - most)) * p + most

    def count(table: pa.Table) -> pa.Table:
        src, dst = (_joined(table[c]) for c in ("one", "two"))
        task = table["task"][0].as_py()
        three = (task // (p * p), task // p % p, task % p)
        ids, at = _numbered(np.concatenate([src, dst]))
        n = len(ids)
        u, v = (x.astype(np.int32) for x in _ordered(at[: len(src)], at[len(src) :], distinct=True))
        del src, dst, at
        of = band[bins.of(ids)]

        def between(x, y):
            """Edges from band x to another, y, whatever way they are kept."""
            there, back = (of[u] == x) & (of[v] == y), (of[u] == y) & (of[v] == x)
            return np.concatenate([u[there], v[back]]), np.concatenate([v[there], u[back]])

        def inside(x):
            own = (of[u] == x) & (of[v] == x)
            a, b = u[own], v[own]
            if orient == "degree":
                degree = np.bincount(a, minlength=n) + np.bincount(b, minlength=n)
                down = degree[a] > degree[b]
                a, b = np.where(down, b, a), np.where(down, a, b)
            return a, b

        x, y, z = three
        if x == z:
            first = second = third = inside(x)
        elif x == y or y == z:
            single, double = (z, x) if x == y else (x, y)
            first = third = between(single, double)
            second = inside(double)
        else:
            first, second, third = between(x, y), between(y, z), between(x, z)
        found = _closed(n, first, second, third)
        hit = np.flatnonzero(found)
        return pa.table({"id": ids[hit], "n": found[hit]})

    # A few large rows for each task, so that tasks are dealt out singly and not by size.
    dealt = _dealt(plan.edges, deal, 0).repartition(_tasks(plan), "task")
    return dealt.groupBy("task").applyInArrow(count, "id long, n long").groupBy("id").agg(F.sum("n").alias("triangles")), plan.edges


def _tasks(plan: Bands) -> int:
    return max(int(plan.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(2 * plan.count, 1_000))


def edge_cells(edges: DataFrame, halves: bool = False) -> DataFrame | None:
    """``(i, j, n, one, two)``: undirected ``edges`` once each, loops left out, as packed arrays by the bands i <= j of their ends; None without edges.

    ``one`` is the lesser end by (band, id). The corners of a triangle in that order lie in bands i <= j <= k, and its edges in the
    cells (i, j), (j, k) and (i, k): see ``closed_cells``. ``halves`` as for ``triangle_counts``.
    """
    ship(edges.sparkSession)
    plan = banded(edges if halves else edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")), True, halves)
    if plan is None:
        return None
    bins, band, p = plan.sources, plan.band, plan.count

    def deal(src, dst):
        s, d = band[bins.of(src)], band[bins.of(dst)]
        return np.arange(len(src)), np.minimum(s, d) * p + np.maximum(s, d)

    def pack(table: pa.Table) -> pa.Table:
        one, two = (_joined(table[c]) for c in ("one", "two"))
        back = band[bins.of(one)] > band[bins.of(two)]
        one, two = np.where(back, two, one), np.where(back, one, two)
        one, two = _ordered(one, two, distinct=True)
        task = table["task"][0].as_py()
        return pa.table({"i": pa.array([task // p], pa.int32()), "j": pa.array([task % p], pa.int32()), "n": [len(one)], "one": [_packed(one)], "two": [_packed(two)]})

    dealt = _dealt(plan.edges, deal, 0).repartition(_tasks(plan), "task")
    return dealt.groupBy("task").applyInArrow(pack, "i int, j int, n long, one binary, two binary")


def closed_cells(*cells: bytes) -> int:
    """Triangles of which the edges lie in the cells (i, j), (j, k) and (i, k), given as ``one`` and ``two`` of each."""
    ends = [_unpacked(x) for x in cells]
    ids, at = _numbered(np.concatenate(ends))
    at = np.split(at, np.cumsum([len(x) for x in ends])[:-1])
    return int(_closed(len(ids), (at[0], at[1]), (at[2], at[3]), (at[4], at[5])).sum()) // 3


class _Rows:
    """Lists of numbers under ``n``, laid out in rows of one width that a task takes at once; free places hold ``n``."""

    def __init__(self, lists: np.ndarray, entries: np.ndarray, n: int, dtype):
        length = np.diff(lists)
        used = int(np.count_nonzero(length))
        # About a quarter of the mean list, so that few places stay free.
        self.width = width = 1 << int(np.clip(np.round(np.log2(max(len(entries), 1) / max(used, 1) / 4)), 0, 5))
        count = -(-length // width)
        self.first = np.append(0, np.cumsum(count)).astype(np.int32)
        self.rows = np.full((int(self.first[-1]), width), n, dtype=dtype)
        self.rows.reshape(-1)[np.arange(len(entries)) + np.repeat(self.first[:-1] * width - lists[:-1], length)] = entries


#: Wedges whose entries and marks stay in the processor's cache.
CACHED_WEDGES = 1 << 17


def _closed(n: int, first, second, third) -> np.ndarray:
    """Triangles at each of ``n`` vertices: a -> b in ``first``, b -> c in ``second``, a -> c in ``third``."""
    found = np.zeros(n, dtype=np.int64)
    if not (len(first[0]) and len(second[0]) and len(third[0])):
        return found
    order = _by(second[0])
    lists = _Rows(_lists(second[0][order], n), second[1][order], n, np.int32)
    order = _by(third[0])
    end, ends = third[1][order], _lists(third[0][order], n)
    order = _by(first[0])
    a, b = first[0][order], first[1][order]
    count = lists.first[b + 1] - lists.first[b]
    used = (count > 0) & (ends[a + 1] > ends[a])
    a, b, count = a[used], b[used], count[used]
    if not len(a):
        return found
    # Sources, each with its edges and the rows of their lists.
    heads = np.append(np.flatnonzero(np.diff(a, prepend=-1)), len(a))
    before = np.append(0, np.cumsum(count))[heads]
    most, lo = max(1, (1 << 25) // (n + 1)), 0
    marks = np.zeros(min(most, len(heads) - 1) * (n + 1), dtype=bool)
    while lo < len(heads) - 1:
        # As many sources as have few wedges together and a row of marks each.
        hi = int(np.searchsorted(before, before[lo] + CACHED_WEDGES // lists.width, "right")) - 1
        hi = max(lo + 1, min(hi, lo + most, len(heads) - 1))
        some, sources = slice(heads[lo], heads[hi]), a[heads[lo:hi]]
        closing = ends[sources + 1] - ends[sources]
        of, place = _ragged(closing)
        marked = of * (n + 1) + end[ends[sources][of] + place]
        marks[marked] = True
        edges = np.repeat(np.arange(hi - lo), np.diff(heads[lo : hi + 1]))
        # A source with very many rows takes them in turns.
        for x, y in _slices(count[some], CACHED_WEDGES // lists.width):
            edge, place = _ragged(count[some][x:y])
            edge += x
            at = lists.rows.take(lists.first[b[some][edge]] + place, axis=0)
            if hi - lo > 1:
                hit = np.flatnonzero(marks.take(at + (edges[edge] * (n + 1))[:, None]))
            else:
                hit = np.flatnonzero(marks.take(at))
            by = np.bincount(edge[hit // lists.width], minlength=len(edges))
            np.add.at(found, at.reshape(-1).take(hit), 1)
            np.add.at(found, a[some], by)
            np.add.at(found, b[some], by)
        marks[marked] = False
        lo = hi
    return found


# Common neighbours


def _dense(wedges: np.ndarray, edges: np.ndarray, others: int) -> np.ndarray:
    """Sources with so many wedges that they get counters of their own, which stay in the processor's cache."""
    return (wedges * 4 >= others) & (wedges >= 16 * edges)


def common_neighbours(edges: DataFrame, keep: Callable, least: int = 1, distinct: bool = True, weights: Callable | None = None, halves: bool = False) -> DataFrame | None:
    """``(n1, n2, common, value)``: pairs of sources n1 < n2 with common targets that ``keep(common, value, d1, d2)`` keeps; None without edges.

    It gets arrays, of pairs with ``least`` common targets at least; ``value`` sums w of ``weights(edges)``, a table ``(dst, w)``, over
    common targets. d1 and d2 are at most the out-degrees, as a task may hold
    part of a source's edges, so it must not drop a pair that it would keep at larger ones. More common targets, more of ``value``
    and smaller degrees never make it drop a pair. Out-degrees follow as rows with n2 null
    and the degree as ``common``. ``distinct`` tells whether parallel edges count once.
    ``halves``: ``edges`` are those of ``PropertyGraph.halves``, and each also leads from dst to src.
    """
    ship(edges.sparkSession)
    plan = banded(edges, halves, halves)
    if plan is None:
        return None
    sources, targets, band, p = plan.sources, plan.targets, plan.band, plan.count
    have = plan.near.sum(1)
    first, others = np.cumsum(have) - have, np.nonzero(plan.near)[1]

    def deal(src, dst):
        bin = targets.of(dst)
        row, place = _ragged(have[bin])
        other, own = others[first[bin][row] + place], band[sources.of(src)][row]
        return row, np.minimum(own, other) * p + np.maximum(own, other)

    def deal_weights(dst, w):
        bin = targets.of(dst)
        row, place = _ragged(have[bin] ** 2)
        n = have[bin][row]
        x, y = others[first[bin][row] + place // n], others[first[bin][row] + place % n]
        up = x <= y
        return row[up], (x * p + y)[up]

    def count(table: pa.Table) -> pa.Table:
        kind = table["kind"].to_numpy()
        edge, heavy = table.filter(pa.array(kind == 0)), table.filter(pa.array(kind == 1))
        if not len(edge):
            return pa.table({"n1": pa.array([], pa.int64()), "n2": pa.array([], pa.int64()), "common": pa.array([], pa.int64()), "value": pa.array([], pa.float64())})
        ids, s = _numbered(_joined(edge["one"]))
        mids, m = _numbered(_joined(edge["two"]))
        task = table["task"][0].as_py()
        x, y = task // p, task % p
        m, s = (x.astype(np.int32) for x in _ordered(m, s, distinct))
        weight = None
        if len(heavy):
            at = _joined(heavy["one"])
            w = np.concatenate([np.frombuffer(v.as_py()) for v in heavy["two"]])
            weight = np.zeros(len(mids))
            place = np.minimum(np.searchsorted(mids, at), len(mids) - 1)
            mine = mids[place] == at
            weight[place[mine]] = w[mine]
        degree = np.bincount(s, minlength=len(ids))
        of = band[sources.of(ids)]
        if x == y:
            rows, other = np.arange(len(s), dtype=np.int32), s
            # Parallel edges lie side by side; a list begins after the last of them.
            new = np.append(np.flatnonzero((m[1:] != m[:-1]) | (s[1:] != s[:-1])) + 1, len(s)).astype(np.int32)
            start, lists = np.repeat(new, np.diff(new, prepend=0)), _lists(m, len(mids))
            stop = lists[m + 1]
        else:
            rows, theirs = np.flatnonzero(of[s] == x).astype(np.int32), np.flatnonzero(of[s] == y)
            other, lists = s[theirs], _lists(m[theirs], len(mids))
            start, stop = lists[m[rows]], lists[m[rows] + 1]
        order = _by(s[rows])
        rows, start, stop = rows[order], start[order], stop[order]
        one, length = s[rows], stop - start
        # The others by a number of their own, so that counters are few.
        names, other = _numbered(other)
        out: list[list] = [[], [], [], []]
        heads = np.append(np.flatnonzero(np.diff(one, prepend=-1)), len(one))
        per = np.diff(np.append(0, np.cumsum(length))[heads])
        dense = _dense(4 * per, np.diff(heads), len(names))  # a wedge takes a fourth of the time there
        wmax, dmin = (1.0 if weight is None else weight.max() * (1 + 1e-9)), degree[names].min() if len(names) else 0

        def floor(d):
            """The fewest common targets with which a pair of a source of this degree may be kept."""
            if not distinct:
                return least
            low, high = least, int(d) + 1
            while low < high:
                c = (low + high) // 2
                low, high = (low, c) if keep(np.array([c]), np.array([c * wmax]), np.array([d]), np.array([dmin]))[0] else (c + 1, high)
            return max(low, least)

        each = degree[one[heads[:-1]]]
        some = _once(np.sort(each))
        floors = np.array([floor(d) for d in some], dtype=np.int64)[np.searchsorted(some, each)] if len(some) else each
        if dense.any():
            packed = _Rows(lists, other, len(names), np.int64)
            width, free = packed.width, len(names)
            mine = m[rows]
            # From the row of the list in which those after the source begin; what lies before them there drops out as lesser.
            begin, end = packed.first[mine] + (start - lists[mine]) // width, packed.first[mine + 1]
            begin, size = np.minimum(begin, end), np.where(length > 0, np.maximum(end - begin, 0), 0)
            # Sources of one degree follow each other.
            own = np.flatnonzero(dense)
            own = own[np.argsort(each[own], kind="stable")]
            theirs, which = _numbered(degree[names])

            def needs(d, top):
                """The fewest common targets with which a pair of a source of this degree and each of the others may be kept."""
                low = np.full(len(theirs), least)
                high = np.full(len(theirs), int(d) + 1) if distinct else low
                while (low < high).any():
                    c, open_ = (low + high) // 2, low < high
                    may = keep(c, c * wmax, np.full(len(c), d), theirs)
                    low, high = np.where(open_ & ~may, c + 1, low), np.where(open_ & may, c, high)
                return np.minimum(np.maximum(low, least), np.iinfo(top).max).astype(top)[which]

            last = None
            # A counter never exceeds the source's edges, or its wedges where edges are parallel.
            high = int((np.diff(heads) if distinct else per)[own].max())
            counter = np.zeros(free + 1, dtype=np.uint16 if high < 1 << 16 else np.int64)
            step, need = counter.dtype.type(1), np.full(free + 1, np.iinfo(counter.dtype).max, dtype=counter.dtype)
            taken, turn = np.add.reduceat(size, heads[:-1]), max(1, WEDGES // width)
            for lo, hi in _slices(taken[own] * width):
                hits, edges_of = [], np.concatenate([np.arange(heads[i], heads[i + 1]) for i in own[lo:hi]])
                edge, place = _ragged(size[edges_of])
                row = begin[edges_of][edge] + place
                ends = np.append(0, np.cumsum(taken[own[lo:hi]]))
                for k, i in enumerate(own[lo:hi].tolist()):
                    counter[:] = 0
                    # A source with very many wedges takes them in turns.
                    turns = [(at, min(at + turn, ends[k + 1])) for at in range(ends[k], ends[k + 1], turn)]
                    for u, v in turns:
                        entries = packed.rows.take(row[u:v], axis=0).reshape(-1)
                        np.add.at(counter, entries, step)
                    counter[free] = 0
                    if x == y:
                        # Those up to the source itself were counted in part.
                        counter[: one[heads[i]] + 1] = 0
                    if each[i] != last:
                        last = each[i]
                        need[:free] = needs(last, need.dtype)
                    passing = counter >= need
                    hit = np.flatnonzero(passing)
                    if not len(hit):
                        continue
                    common = counter[hit].astype(np.int64)
                    sums = common.astype(np.float64)
                    if weight is not None:
                        sums = np.zeros(len(hit))
                        for u, v in turns:
                            if len(turns) > 1:
                                entries = packed.rows.take(row[u:v], axis=0).reshape(-1)
                            used = np.flatnonzero(passing.take(entries))
                            sums += np.bincount(entries[used], weights=weight[mine[edges_of[edge[u:v][used // width]]]], minlength=free)[hit]
                    hits.append((np.full(len(hit), one[heads[i]]), hit, common, sums))
                if not hits:
                    continue
                a, b, common, sums = (np.concatenate(v) for v in zip(*hits))
                b = names[b]
                kept = np.flatnonzero(keep(common, sums, degree[a], degree[b]))
                a, b = ids[a[kept]], ids[b[kept]]
                for held, v in zip(out, (np.minimum(a, b), np.maximum(a, b), common[kept], sums[kept])):
                    held.append(v)
            del packed
        if dense.any():
            rest = np.repeat(~dense, np.diff(heads))
            rows, start, stop, one, length = rows[rest], start[rest], stop[rest], one[rest], length[rest]
            heads = np.append(np.flatnonzero(np.diff(one, prepend=-1)), len(one))
            per, floors = per[~dense], floors[~dense]
        for lo, hi in _slices(per):
            some = slice(heads[lo], heads[hi])
            n = length[some]
            at = np.arange(n.sum()) + np.repeat(start[some] - (np.cumsum(n) - n), n)
            cell = np.repeat(np.repeat(np.arange(hi - lo), np.diff(heads[lo : hi + 1])) * len(names), n) + other[at]
            w = None if weight is None else np.repeat(weight[m[rows[some]]], n)
            if not len(cell):
                continue
            if w is None:
                cell.sort()
            else:
                order = _by(cell)
                cell, w = cell[order], w[order]
            first_of = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
            counts = np.diff(first_of, append=len(cell))
            hit = np.flatnonzero(counts >= floors[lo + cell[first_of] // len(names)])
            if not len(hit):
                continue
            common, cell = counts[hit], cell[first_of[hit]]
            sums = common.astype(np.float64) if w is None else np.add.reduceat(w, first_of)[hit]
            a, b = one[heads[lo + cell // len(names)]], names[cell % len(names)]
            kept = np.flatnonzero(keep(common, sums, degree[a], degree[b]))
            a, b = ids[a[kept]], ids[b[kept]]
            for held, v in zip(out, (np.minimum(a, b), np.maximum(a, b), common[kept], sums[kept])):
                held.append(v)
        pairs = [np.concatenate(v) if v else np.zeros(0) for v in out]
        tables = [pa.table({"n1": pairs[0].astype(np.int64), "n2": pa.array(pairs[1].astype(np.int64)), "common": pairs[2].astype(np.int64), "value": pairs[3].astype(np.float64)})]
        if x == y:
            tables.append(pa.table({"n1": ids, "n2": pa.nulls(len(ids), pa.int64()), "common": degree.astype(np.int64), "value": np.zeros(len(ids))}))
        return pa.concat_tables(tables)

    dealt = _dealt(plan.edges, deal, 0, halves)
    if weights is not None:
        dealt = dealt.unionByName(_dealt(weights(plan.edges).select(F.col("dst").cast("long").alias("dst"), F.col("w").cast("double").alias("w")), deal_weights, 1))
    return dealt.repartition(_tasks(plan), "task").groupBy("task").applyInArrow(count, "n1 long, n2 long, common long, value double")
