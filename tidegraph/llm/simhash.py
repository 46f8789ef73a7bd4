"""SimHash near-duplicate detection over deletion-variant signatures.

A 64-bit fingerprint is cut into few segments, so few that of two fingerprints within the allowed distance at least one
segment differs by one bit at most: two segments for 3 bits, three for 5. Each segment is indexed once for each of its
bits with that bit wild, the variants meet in an equality join, and full fingerprints are then compared.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from tidegraph.operators.components import star_components
from tidegraph.runtime import Scratch, materialize, ship

#: Members of one signature that are compared in one array; more are dealt out in blocks of this size.
BLOCK = 512


def segments(distance: int) -> list[tuple[int, int]]:
    """(first bit, width) of each segment; ``distance`` bits over so many segments leave one with one bit at most."""
    count = max(2, (distance + 2) // 2)
    edges = [64 * i // count for i in range(count + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:])]


def shingles(words: list[bytes], width: int) -> list[bytes]:
    """Space-joined runs of ``width`` words; of fewer words the whole sequence, of none nothing."""
    if not words:
        return []
    if len(words) <= width:
        return [b" ".join(words)]
    return [b" ".join(x) for x in zip(*(words[i:] for i in range(width)))]


def fingerprint(features: list[bytes], seed: int = 42) -> int:
    """Bit i is 1 if more than half of the XXH64 hashes have it; no features give 0."""
    if not features:
        return 0
    digest = xxhash.xxh64_digest
    total = np.zeros(64, dtype=np.int64)
    for at in range(0, len(features), 1 << 15):
        part = features[at : at + (1 << 15)]
        total += np.unpackbits(np.frombuffer(b"".join([digest(x, seed) for x in part]), dtype=np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(total * 2 > len(features)).tobytes(), "big")


def _binary(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def _signed(values: list[int]) -> pa.Array:
    return pa.array(np.array(values, dtype=np.uint64).view(np.int64))


def shingle_fingerprints(docs: DataFrame, width: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, fp)``: the fingerprint of each whole text's word shingles, repeats included, A-Z lower-cased.

    A null or empty text has fingerprint zero. Other columns are not read.
    """
    ship(docs.sparkSession)

    def run(batches):
        for batch in batches:
            out = [fingerprint(shingles(x.lower().split(), width), seed) for x in _binary(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), _signed(out)], ["id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id long, fp long")


def _variants(nodes: DataFrame, distance: int) -> DataFrame:
    """64 rows for each node: the segment of each bit of its fingerprint with that bit wild, and the bit's number as a tag."""
    owner = [(a, w) for a, w in segments(distance) for _ in range(w)]
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    masks = F.array(*[F.lit(signed((((1 << w) - 1) << a) & ~(1 << bit))) for bit, (a, w) in enumerate(owner)])
    firsts = F.array(*[F.lit(a) for a, _ in owner])
    rows = nodes.select("id", "fp", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("bit"))
    kept = F.col("fp").bitwiseAND(F.element_at(masks, F.col("bit") + 1))
    packed = F.call_function("shiftrightunsigned", kept, F.element_at(firsts, F.col("bit") + 1))
    return rows.select(packed.bitwiseOR(F.shiftleft(F.col("bit").cast("long"), 33)).alias("key"), "id")


class _Forest:
    """Union-find over the members of one array."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        if x == y:
            return False
        self.up[max(x, y)] = min(x, y)
        return True


def _spanning(key: int, ids: np.ndarray, fp: np.ndarray, sketch: np.ndarray | None, distance: int, agree: int) -> list[tuple[int, int]]:
    """Links from the smallest id of each group that one signature connects to the group's others. fp: (members,) unsigned; sketch: (members, bytes) or None.

    A pair belongs to the signature whose wild bit is the only one its segment differs in; equal segments belong to the
    segment's first bit. So no pair is compared twice for one segment.
    """
    bit = key >> 33
    first, width = next((a, w) for a, w in segments(distance) if a <= bit < a + w)
    own = np.uint64(((1 << width) - 1) << first)
    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], fp[order]
    sketch = None if sketch is None else sketch[order]
    forest = _Forest(len(ids))
    for i in range(len(ids) - 1):
        diff = x[i + 1 :] ^ x[i]
        inside = diff & own
        fits = inside == np.uint64(1 << bit)
        if bit == first:
            fits |= inside == 0
        fits &= np.bitwise_count(diff) <= distance
        near = np.flatnonzero(fits) + i + 1
        if sketch is not None and len(near):
            near = near[(sketch[near] == sketch[i]).sum(1) >= agree]
        for j in near:
            forest.join(i, int(j))
    tops = [forest.root(i) for i in range(len(ids))]
    return [(int(ids[t]), int(ids[i])) for i, t in enumerate(tops) if ids[t] != ids[i]]


def _may_reach(size: int, sizes: np.ndarray, mark: np.ndarray, marks: np.ndarray, similarity: float) -> np.ndarray:
    """False only for sets that cannot reach ``similarity``: their sizes, or the shingles in which their parity maps differ, forbid it."""
    apart = np.bitwise_count(marks ^ mark).sum(1)
    return (np.minimum(sizes, size) >= similarity * np.maximum(sizes, size) - 1e-9) & (apart <= (sizes + size) * ((1 - similarity) / (1 + similarity)) + 1e-6)


#: Rows of two longs that are sent to every executor; a larger side is shuffled.
BROADCAST_ROWS = 200_000


def _counted(table: Scratch) -> DataFrame:
    """The table, to be broadcast if its counted rows are few."""
    return F.broadcast(table.df) if table.df.count() <= BROADCAST_ROWS else table.df


def near_links(nodes: DataFrame, distance: int = 3, sketch: str | None = None, agree: int = 0) -> Scratch:
    """``nodes(id, fp)`` -> links ``(a, b)`` that connect all nodes within ``distance`` bits, as a written table.

    The links span: two nodes are connected by them if and only if they are by near pairs. Each signature gives links from
    the smallest of its members, so that those of a dense group fall together, and never all its pairs. ``sketch`` names a
    binary column of which at least ``agree`` bytes must be equal too. Signatures held by over ``BLOCK`` nodes are dealt out in blocks, and every pair of blocks is
    compared in a task of its own.
    """
    ship(nodes.sparkSession)
    keys = _variants(nodes, distance)
    held = materialize(keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "held")
    columns = ["id", "fp", *([sketch] if sketch else [])]
    members = materialize(keys.join(_counted(held), "key").join(nodes.select(*columns), "id"), "signatures")
    held.drop()

    def spanning(key, ids, fp, marks):
        marks = None if marks is None else np.frombuffer(b"".join(marks), dtype=np.uint8).reshape(len(ids), -1)
        return _spanning(key, ids, fp.view(np.uint64), marks, distance, agree)

    def small(batches):
        for batch in batches:
            found: dict[tuple[int, int], None] = {}
            lists = batch.column(1)
            flat, ends = lists.flatten(), lists.offsets.to_numpy()
            ends = ends - ends[0]
            if len(flat):
                ids, fp = flat.field(0).to_numpy(), flat.field(1).to_numpy()
                marks = flat.field(2).to_pylist() if sketch else None
                for key, a, b in zip(batch.column(0).to_pylist(), ends, ends[1:]):
                    found.update(dict.fromkeys(spanning(key, ids[a:b], fp[a:b], None if marks is None else marks[a:b])))
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in found], pa.int64()), pa.array([y for _, y in found], pa.int64())], ["a", "b"])

    def blocks(table: pa.Table) -> pa.Table:
        found = spanning(table["key"][0].as_py(), table["id"].to_numpy(), table["fp"].to_numpy(), table[sketch].to_pylist() if sketch else None)
        return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([y for _, y in found], pa.int64())})

    grouped = (
        members.df.where(F.col("n") <= BLOCK).groupBy("key").agg(F.collect_list(F.struct(*columns)).alias("m")).where("size(m) > 1")
    )
    hot = _in_blocks(members.df.where(F.col("n") > BLOCK), "n").groupBy("key", "one", "two").applyInArrow(blocks, "a long, b long")
    links = materialize(grouped.mapInArrow(small, "a long, b long").unionByName(hot).distinct(), "near")
    members.drop()
    return links


def _in_blocks(rows: DataFrame, size: str) -> DataFrame:
    """Rows of groups of ``size`` members, each copied to every pair of blocks ``(one, two)`` that its own block is part of."""
    count = F.ceil(F.col(size) / BLOCK).cast("int")
    return (
        rows.withColumn("own", F.pmod(F.xxhash64("id"), count).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), count - 1)))
        .withColumn("one", F.least("own", "other"))
        .withColumn("two", F.greatest("own", "other"))
    )


def near_components(docs: DataFrame, width: int = 3, distance: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` for every document: groups linked at ``distance`` or fewer differing bits.

    Equal fingerprints are one node, so copies cost nothing further. Documents with a null id have no row. A document
    without words has fingerprint zero and links like any other; an empty table gives an empty result.
    """
    prints = materialize(shingle_fingerprints(docs.where(F.col(id_col).isNotNull()), width, seed, id_col, text_col), "prints")
    nodes = materialize(prints.df.groupBy("fp").agg(F.min("id").alias("id")), "nodes")
    links = near_links(nodes.df, distance)
    found = star_components(links.df)
    links.drop()
    classes = nodes.df.join(found, "id", "left").select("fp", F.coalesce("component", "id").alias("component_id"))
    return prints.df.join(classes, "fp").select(
        F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


#: Bits of a text's parity map; each shingle flips one, so two maps differ in no more bits than their sets differ in shingles.
PARITY_BITS = 512
#: Bytes of the sketch of a text's shingles, and how many must agree: those of a pair at similarity 0.8 agree in 0.8 of them, of unrelated texts in hardly any.
SKETCH_BYTES, SKETCH_AGREE = 16, 6
#: Documents whose shingles are counted to put frequent ones last, and the most of them that are remembered.
ORDER_DOCS, ORDER_SHINGLES = 20_000, 200_000
#: Hashes of words that a task remembers.
KNOWN_WORDS = 1_000_000
_ODD = np.uint64(0x9E3779B97F4A7C15)


class WordSets:
    """Turns lower-cased texts into hashes of their words and shingles; a word's hash is computed once in a task."""

    def __init__(self, width: int):
        self.width = width
        self.known: dict[bytes, int] = {}

    def words(self, raw: bytes) -> np.ndarray:
        """XXH64 of each word of a text, in order."""
        found = raw.lower().split()
        if len(self.known) > KNOWN_WORDS:
            self.known.clear()
        for w in set(found).difference(self.known):
            self.known[w] = xxhash.xxh64_intdigest(w)
        return np.fromiter(map(self.known.__getitem__, found), dtype=np.uint64, count=len(found))

    def shingles(self, words: np.ndarray) -> np.ndarray:
        """Sorted distinct 64-bit hashes of the runs of ``width`` words; of fewer words of the whole sequence, of none nothing."""
        wide = min(self.width, len(words))
        if not wide:
            return words
        n = len(words) - wide + 1
        total = words[:n].copy()
        for k in range(1, wide):
            total = total * _ODD + words[k : k + n]
        total = (total ^ (total >> np.uint64(31))) * _ODD
        return np.unique(total ^ (total >> np.uint64(29)))


def word_fingerprint(words: np.ndarray) -> int:
    """SimHash of a text's distinct words, each weighted by the root of its count."""
    own, counts = np.unique(words, return_counts=True)
    weights, total = np.sqrt(counts), np.zeros(64)
    for at in range(0, len(own), 1 << 15):
        bits = np.unpackbits(own[at : at + (1 << 15)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        total += weights[at : at + (1 << 15)] @ bits
    return int.from_bytes(np.packbits(total * 2 > weights.sum()).tobytes(), "big")


def parity_map(hashes: np.ndarray) -> bytes:
    flips = np.bincount((hashes & np.uint64(PARITY_BITS - 1)).astype(np.int64), minlength=PARITY_BITS)
    return np.packbits((flips & 1).astype(np.uint8)).tobytes()


def sketch_of(hashes: np.ndarray) -> bytes:
    """The low byte of the least hash in each of SKETCH_BYTES permutations."""
    odd = (2 * np.arange(SKETCH_BYTES, dtype=np.uint64) + np.uint64(1)) * _ODD | np.uint64(1)
    mixed = (hashes ^ (hashes >> np.uint64(29))) * odd[:, None]
    return (mixed ^ (mixed >> np.uint64(32))).min(1).astype(np.uint8).tobytes()


#: Two sets must share one token of their prefixes, and one more for so many tokens of the smaller set; prefixes are longer by as much.
SHARE_EVERY = 50


def prefix_length(size: int, similarity: float) -> int:
    """Of two sets at ``similarity`` or more, the first so many members of each, in any common order, share 1 + size / SHARE_EVERY of the smaller set."""
    return min(size, size - math.ceil(similarity * size - 1e-9) + 1 + size // SHARE_EVERY)


def near_duplicate_groups(docs: DataFrame, width: int = 5, similarity: float = 0.8, distance: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, group_id)`` of every document with an id: groups linked at Jaccard ``similarity`` or more of word shingles.

    SimHash fingerprints of the words give candidates within ``distance`` bits by deletion-variant signatures, cheaply and
    for most members of large groups. An exact prefix-filter join finds all other pairs, namely those across the groups so
    far, so the result is that of comparing all pairs. Candidates of both kinds are then held against ``similarity`` on
    their whole shingle sets. Texts that are equal word for word are one node. group_id is the group's smallest id. Texts
    without words stay alone (they are no copies of anything); rows with a null id are not in the result.
    """
    ship(docs.sparkSession)
    texts = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    scanned = materialize(_scan(texts, width, similarity), "scanned")
    worded = scanned.df.where("size > 0")
    held = ("size", "parity", "sketch", "fp", "prefix")
    classes = materialize(worded.groupBy("key").agg(F.min("id").alias("id"), *[F.first(c).alias(c) for c in held]), "classes")
    members = materialize(scanned.df.select("id", "key"), "members")
    scanned.drop()
    near = near_links(classes.df, distance, "sketch", SKETCH_AGREE)
    candidates = materialize(star_components(near.df), "candidates")
    near.drop()
    met = _prefix_links(classes.df, candidates, similarity)
    together = met.df.unionByName(candidates.df.where("id <> component").select(F.col("component").alias("a"), F.col("id").alias("b")))
    groups = materialize(star_components(together), "groups")
    met.drop()
    candidates.drop()
    links = materialize(_verified_links(texts, groups, width, similarity), "verified")
    groups.drop()
    whole = star_components(links.df)
    links.drop()
    grouped = classes.df.select("key", "id").join(whole, "id", "left").select("key", F.coalesce("component", "id").alias("group_id"))
    return members.df.join(grouped, "key", "left").select(F.col("id").alias("doc_id"), F.coalesce("group_id", "id").alias("group_id"))


def _scan(texts: DataFrame, width: int, similarity: float) -> DataFrame:
    """``(id, key, size, parity, sketch, fp, prefix)`` of each text: its class, its word fingerprint, and size, parity map, sketch and prefix of its shingles, rare ones first."""
    frequent = texts.sparkSession.sparkContext.broadcast(_frequent(texts, width))

    def run(batches):
        known, times = frequent.value
        sets = WordSets(width)
        for batch in batches:
            keys, sizes, marks, sketches, prints, prefixes = [], [], [], [], [], []
            for raw in _binary(batch.column(1)):
                words = sets.words(raw)
                own = sets.shingles(words)
                keys.append(hashlib.md5(words.tobytes()).digest())
                sizes.append(len(own))
                marks.append(parity_map(own))
                sketches.append(sketch_of(own) if len(own) else bytes(SKETCH_BYTES))
                prints.append(word_fingerprint(words) if len(own) else 0)
                if len(known) and len(own):
                    at = np.minimum(np.searchsorted(known, own), len(known) - 1)
                    own = own[np.argsort(np.where(known[at] == own, times[at], 0), kind="stable")]
                prefixes.append(own[: prefix_length(len(own), similarity)].view(np.int64))
            ends = np.cumsum([0, *map(len, prefixes)]).astype(np.int32)
            flat = np.concatenate(prefixes) if prefixes else np.zeros(0, dtype=np.int64)
            columns = [batch.column(0), pa.array(keys, pa.binary()), pa.array(sizes, pa.int32()), pa.ListArray.from_arrays(pa.array(np.arange(len(marks) + 1, dtype=np.int32) * (PARITY_BITS // 64)), pa.array(np.frombuffer(b"".join(marks), dtype=np.int64))), pa.array(sketches, pa.binary()), _signed(prints), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))]
            yield pa.RecordBatch.from_arrays(columns, ["id", "key", "size", "parity", "sketch", "fp", "prefix"])

    return texts.mapInArrow(run, "id long, key binary, size int, parity array<long>, sketch binary, fp long, prefix array<long>")


def _frequent(texts: DataFrame, width: int) -> np.ndarray:
    """Hashes of shingles that recur in a sample of the texts, sorted by hash with how often: (2, n).

    The prefix filter is exact for any order of the shingles; this one keeps the groups of the join small.
    """
    step = max(1, texts.count() // ORDER_DOCS)
    sample = texts.where(F.pmod(F.xxhash64("id"), F.lit(step)) == 0).select("text")

    def run(batches):
        sets = WordSets(width)
        for batch in batches:
            own = [sets.shingles(sets.words(x)) for x in _binary(batch.column(0))]
            flat = np.concatenate(own) if own else np.zeros(0, dtype=np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(flat.view(np.int64))], ["token"])

    counts = sample.mapInArrow(run, "token long").groupBy("token").agg(F.count(F.lit(1)).alias("n")).where("n > 2")
    rows = counts.orderBy(F.desc("n"), "token").limit(ORDER_SHINGLES).toArrow()
    token = rows["token"].to_numpy().view(np.uint64)
    order = np.argsort(token)
    return np.stack([token[order], rows["n"].to_numpy().astype(np.uint64)[order]])


def _prefix_links(classes: DataFrame, candidates: Scratch, similarity: float) -> Scratch:
    """Pairs ``(a, b)`` of different candidate groups, all of those at ``similarity`` or more among them, as a written table.

    Sets that similar share shingles of their prefixes, large sets more than a few, so that long texts which meet by chance
    drop out. Sizes, the places of the first shared shingle and the parity maps bound the overlap and drop most others; none
    of these bounds can drop a true pair.
    """
    tokens = classes.select("id", "size", F.posexplode("prefix").alias("place", "token"))
    shared = materialize(tokens.groupBy("token").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "shared")
    found = classes.select("id", "parity").join(candidates.df, "id", "left").select("id", "parity", F.coalesce("component", "id").alias("found"))
    rows = materialize(tokens.join(_counted(shared), "token").join(found, "id"), "prefixes")
    shared.drop()
    between = materialize(rows.df.groupBy("token").agg(F.min("found").alias("least"), F.max("found").alias("most")).where("least < most").select("token"), "between")
    count = F.ceil(F.col("n") / BLOCK).cast("int")
    spread = rows.df.join(_counted(between), "token").withColumn("count", count)
    left = spread.withColumn("own", F.pmod(F.xxhash64("id"), F.col("count")).cast("int")).alias("x")
    right = spread.withColumn("own", F.explode(F.sequence(F.lit(0), F.col("count") - 1))).alias("y")
    x, y = (lambda c: F.col(f"x.{c}")), (lambda c: F.col(f"y.{c}"))
    total = x("size") + y("size")
    apart = F.lit(0)
    for k in range(PARITY_BITS // 64):
        apart = apart + F.bit_count(F.get(x("parity"), F.lit(k)).bitwiseXOR(F.get(y("parity"), F.lit(k))))
    near = (
        (x("id") < y("id")) & (x("found") != y("found"))
        & (F.least(x("size"), y("size")) >= similarity * F.greatest(x("size"), y("size")) - 1e-9)
        & (apart <= total * ((1 - similarity) / (1 + similarity)) + 1e-6)
    )
    joined = left.join(right, (x("token") == y("token")) & (x("own") == y("own")) & near)
    reach = F.least(x("size") - x("place"), y("size") - y("place")) - total * (similarity / (1 + similarity))
    shared = joined.select(x("id").alias("a"), y("id").alias("b"), F.least(x("size"), y("size")).alias("size"), reach.alias("reach"))
    enough = (F.col("n") >= 1 + F.floor(F.col("size") / SHARE_EVERY)) & (F.col("reach") >= -1e-6)
    pairs = shared.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"), F.max("reach").alias("reach"), F.max("size").alias("size")).where(enough)
    pairs = materialize(pairs.select("a", "b"), "met")
    rows.drop()
    between.drop()
    return pairs


def _verified_links(texts: DataFrame, groups: Scratch, width: int, similarity: float) -> DataFrame:
    """Links at ``similarity`` or more inside each candidate group, spanning; groups over BLOCK go in pairs of blocks."""

    def hashed(batches):
        sets = WordSets(width)
        for batch in batches:
            own = [sets.shingles(sets.words(x)).tobytes() for x in _binary(batch.column(2))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(own, pa.binary())], ["id", "component", "shingles"])

    def compare(table: pa.Table) -> pa.Table:
        ids = table["id"].to_pylist()
        order = sorted(range(len(ids)), key=ids.__getitem__)
        ids = [ids[i] for i in order]
        sets = [np.frombuffer(table["shingles"][i].as_py(), dtype=np.uint64) for i in order]
        sizes = np.array([len(x) for x in sets], dtype=np.int64)
        marks = np.frombuffer(b"".join(parity_map(x) for x in sets), dtype=np.uint64).reshape(len(sets), -1)
        forest, a, b = _Forest(len(ids)), [], []
        for i in range(len(ids) - 1):
            for j in np.flatnonzero(_may_reach(sizes[i], sizes[i + 1 :], marks[i], marks[i + 1 :], similarity)) + i + 1:
                j = int(j)
                if ids[i] == ids[j] or forest.root(i) == forest.root(j):
                    continue
                both = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                if both >= similarity * (sizes[i] + sizes[j] - both) and forest.join(i, j):
                    a.append(ids[i])
                    b.append(ids[j])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    sizes = groups.df.groupBy("component").agg(F.count(F.lit(1)).alias("n"))
    sets = texts.join(_counted(groups), "id").select("id", "component", "text").mapInArrow(hashed, "id long, component long, shingles binary")
    return _in_blocks(sets.join(sizes, "component"), "n").groupBy("component", "one", "two").applyInArrow(compare, "a long, b long").distinct()
