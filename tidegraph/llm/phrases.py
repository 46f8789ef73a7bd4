"""Substring dedup by repeated-phrase automata.

Recurring passages are confirmed first: every window of words is represented by the rarest-hashed short gram in it (its
anchor), and the words under the windows of one anchor are its region. Of regions whose anchor recurs in another text,
equal ones become one, the windows in them are hashed whole, and those seen in two texts make up the passages, each kept
where it first occurs. Their windows are compiled, as sequences of words, into Aho-Corasick automata sharded by anchor, several for a
shard of many windows, and the regions stream through the automata of their shard. So what is removed has been compared word by word, not by hash.
"""

from __future__ import annotations

import hashlib
import re

import ahocorasick
import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from tidegraph.runtime import materialize, ship

GRAM = 12
#: Windows of passages compiled into one automaton (a shard with over twice as many has several), and regions that stream through one copy of it.
SHARD_WINDOWS = 20_000
STREAM_REGIONS = 20_000

_WORD = re.compile(rb"[^\x20\x09-\x0D]+")
_ODD = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9))


def split_words(raw: bytes) -> list[bytes]:
    """Runs of bytes other than the six ASCII white-space characters."""
    return raw.split()


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(29))


def word_hashes(words: list[bytes]) -> np.ndarray:
    digest = xxhash.xxh64_digest
    return np.frombuffer(b"".join([digest(w) for w in words]), dtype="<u8")


def run_hashes(h: np.ndarray, width: int, which: int) -> np.ndarray:
    """A 64-bit hash of every run of ``width`` word hashes; ``which`` picks one of three independent ones."""
    n = len(h) - width + 1
    if which:
        h = _mix(h + _ODD[which])
    odd = _ODD[which]
    if width <= 16:
        total = np.zeros(n, dtype=np.uint64)
        for j in range(width):
            total = total * odd + h[j : n + j]
        return _mix(total)
    power = np.ones(len(h), dtype=np.uint64)
    power[1:] = np.cumprod(np.full(len(h) - 1, odd, dtype=np.uint64))
    inverse = np.uint64(pow(int(odd), -1, 1 << 64))
    back = np.ones(n, dtype=np.uint64)
    back[1:] = np.cumprod(np.full(n - 1, inverse, dtype=np.uint64))
    sums = np.zeros(len(h) + 1, dtype=np.uint64)
    sums[1:] = np.cumsum(h * power)
    return _mix((sums[width:] - sums[:n]) * back)


def anchors(words: list[bytes], window: int) -> tuple[np.ndarray, np.ndarray]:
    """(anchor hash, first window) of each run of windows that one anchor represents, in order."""
    if len(words) < window:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    gram = min(GRAM, window)
    g = run_hashes(word_hashes(words), gram, 0)
    span = window - gram + 1
    n = len(words) - window + 1
    place = np.empty(n, dtype=np.int64)
    for at in range(0, n, 1 << 14):
        part = np.lib.stride_tricks.sliding_window_view(g[at : min(at + (1 << 14), n) + span - 1], span)
        place[at : at + len(part)] = part.argmin(1) + np.arange(at, at + len(part))
    first = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
    return g[place[first]], first


def _raw(column) -> list[bytes]:
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def _longs(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64))


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *[len(x) for x in parts]])
    flat = np.concatenate(parts) if parts else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), _longs(flat))


class Automaton:
    """The windows of a shard's passages, compiled over word numbers; ``find`` gives the stretches of a text that they hold."""

    def __init__(self, window: int):
        self.window = window
        self.trie = ahocorasick.Automaton(ahocorasick.STORE_INTS, ahocorasick.KEY_SEQUENCE)
        self.numbers: dict[str, int] = {}
        self.sources: list[int] = []

    def add(self, source: int, text: str) -> None:
        """Every window of a passage (words joined by one space); of a window that is there already the smallest source stays."""
        numbers = self.numbers
        ids = tuple([numbers.setdefault(w, len(numbers) + 1) for w in text.split(" ")])
        self.sources.append(source)
        for at in range(len(ids) - self.window + 1):
            key = ids[at : at + self.window]
            held = self.trie.get(key, None)
            if held is None or self.sources[held] > source:
                self.trie.add_word(key, len(self.sources) - 1)

    def compile(self) -> None:
        if len(self.trie):
            self.trie.make_automaton()

    def find(self, text: str) -> list[tuple[int, int, int]]:
        """(first word, end, source) of each window of ``text`` that is in the automaton; words it does not know match nothing."""
        if not len(self.trie):
            return []
        known = self.numbers.get
        ids = tuple([known(w, 0) for w in text.split(" ")])
        return [(last + 1 - self.window, last + 1, self.sources[k]) for last, k in self.trie.iter(ids)]


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def repeated_spans(docs: DataFrame, window: int = 50, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame, DataFrame]:
    """The word spans of each text that repeat an earlier one.

    Returns ``(whole, spans, suspects)``. whole: ``doc_id, n_words, whole_sha256, copy`` of every document with an id, where
    ``copy`` tells that all its words stand in an earlier document in the same order (such a document of a window or more
    has all its words covered). spans: ``doc_id, edges`` of other documents with covered words, where
    edges are first words and ends (exclusive) in turn, from 0, not merged. suspects: ``doc_id, words`` of the documents spans can be about, the words joined
    by one space.

    A word is covered if it stands in a window of ``window`` words that also starts in a document with a smaller id.
    Null and empty texts have no words; texts shorter than a window are never covered. Ids should be unique; of rows
    that share an id each is cut by the spans of the id, and the query form gives each a row.
    """
    spark = docs.sparkSession
    ship(spark)
    texts = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))

    def scan(batches):
        for batch in batches:
            counts, shas, keys, hashes, firsts = [], [], [], [], []
            for raw in _raw(batch.column(1)):
                words = split_words(raw)
                whole = hashlib.sha256(b" ".join(words))
                counts.append(len(words))
                shas.append(whole.hexdigest())
                keys.append(whole.digest()[:16])
                a, f = anchors(words, window)
                hashes.append(a)
                firsts.append(f)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(counts, pa.int64()), pa.array(shas), pa.array(keys, pa.binary()), _lists(hashes), _lists(firsts)],
                ["doc_id", "n_words", "whole_sha256", "key", "anchors", "firsts"],
            )

    scanned = materialize(texts.mapInArrow(scan, "doc_id long, n_words long, whole_sha256 string, key binary, anchors array<long>, firsts array<long>"), "scanned")
    originals = materialize(scanned.df.groupBy("key").agg(F.min("doc_id").alias("original")), "originals")
    long_ones = scanned.df.where(F.size("anchors") > 0).join(originals.df.select(F.col("original").alias("doc_id")), "doc_id", "left_semi")
    nexts = F.array_append(F.slice("firsts", F.lit(2), F.size("firsts")), F.col("n_words") - window + 1)
    placed = long_ones.select("doc_id", F.explode(F.arrays_zip("anchors", "firsts", nexts.alias("nexts"))).alias("a")).select(
        "doc_id", F.col("a.anchors").alias("anchor"), F.col("a.firsts").alias("first"), F.col("a.nexts").alias("next")
    )
    recurring = placed.groupBy("anchor").agg(F.min("doc_id").alias("earliest"), F.max("doc_id").alias("latest")).where("earliest < latest")
    recurring = materialize(recurring.select("anchor"), "recurring")  # a plain side, so that the join can split a hot anchor
    flagged = materialize(placed.join(recurring.df, "anchor"), "flagged")
    per_doc = flagged.df.groupBy("doc_id").agg(F.collect_list(F.struct("anchor", "first", "next")).alias("runs"))

    def normalise(batches):
        for batch in batches:
            joined = [b" ".join(split_words(x)) for x in _raw(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(joined, pa.binary()).cast(pa.string()), batch.column(2)], ["doc_id", "words", "runs"])

    runs_type = "array<struct<anchor:long,first:long,next:long>>"
    suspects = materialize(texts.join(per_doc, "doc_id").mapInArrow(normalise, f"doc_id long, words string, runs {runs_type}"), "suspects")

    def cut_regions(with_text: bool):
        def run(batches):
            for batch in batches:
                docs_, firsts, anchor, out = [], [], [], []
                for doc, raw, runs in zip(batch.column(0).to_pylist(), _raw(batch.column(1)), batch.column(2).to_pylist()):
                    gaps = np.flatnonzero(np.frombuffer(raw, np.uint8) == 32)
                    starts, ends = np.r_[0, gaps + 1], np.r_[gaps, len(raw)]
                    for r in runs:
                        if r["next"] + window - 2 >= len(ends):
                            continue  # of another text under the same id
                        region = raw[starts[r["first"]] : ends[r["next"] + window - 2]]
                        docs_.append(doc)
                        firsts.append(r["first"])
                        anchor.append(r["anchor"])
                        out.append(region if with_text else xxhash.xxh3_128_digest(region))
                columns = [pa.array(docs_, pa.int64()), pa.array(firsts, pa.int64()), pa.array(anchor, pa.int64())]
                last = pa.array(out, pa.binary())
                yield pa.RecordBatch.from_arrays([*columns, last.cast(pa.string()) if with_text else last], ["doc_id", "first", "anchor", "region"])

        return run

    places = "doc_id long, first long, anchor long"
    regions = materialize(
        suspects.df.mapInArrow(cut_regions(True), f"{places}, region string")
        .groupBy("region", "anchor")
        .agg(F.min(F.struct("doc_id", "first")).alias("at"), F.max("doc_id").alias("latest"))
        .select("at.*", "latest", "anchor", "region"),
        "regions",
    )

    def hash_windows(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 2_000):
                batch = whole.slice(at, 2_000)
                lists = [x.split(b" ") for x in _raw(batch.column(3))]
                sizes = np.array([len(x) for x in lists], dtype=np.int64)
                h = word_hashes([w for x in lists for w in x])
                n = sizes - window + 1
                starts = np.cumsum(sizes) - sizes
                offset = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                place = np.repeat(starts, n) + offset  # windows over the seam of two regions are left out
                one, two = run_hashes(h, window, 1)[place], run_hashes(h, window, 2)[place]
                doc, first, latest = (pa.array(np.repeat(batch.column(i).to_numpy(), n)) for i in range(3))
                yield pa.RecordBatch.from_arrays([_longs(one), _longs(two), doc, latest, first, pa.array(offset.astype(np.int32))], ["h1", "h2", "doc_id", "latest", "first", "offset"])

    windows = regions.df.select("doc_id", "first", "latest", "region").mapInArrow(hash_windows, "h1 long, h2 long, doc_id long, latest long, first long, offset int")
    recur = windows.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "first", "offset")).alias("w"), F.max("latest").alias("latest")).where("w.doc_id < latest")
    confirmed = materialize(recur.groupBy("w.doc_id", "w.first").agg(F.collect_list("w.offset").alias("offsets")), "confirmed")
    total = confirmed.df.agg(F.sum(F.size("offsets"))).first()[0] or 0
    shards = max(1, -(-total // SHARD_WINDOWS))
    shard = F.pmod(F.xxhash64("anchor"), F.lit(shards)).cast("int")

    def cut_passages(batches):
        for batch in batches:
            docs_, shards_, out = [], [], []
            for doc, own, region, offsets in zip(*(batch.column(i).to_pylist() for i in range(4))):
                words = region.split(" ")
                at = np.unique(np.array(offsets, dtype=np.int64))
                for run in np.split(at, np.flatnonzero(np.diff(at) > 1) + 1):
                    docs_.append(doc)
                    shards_.append(own)
                    out.append(" ".join(words[run[0] : run[-1] + window]))
            yield pa.RecordBatch.from_arrays([pa.array(docs_, pa.int64()), pa.array(shards_, pa.int32()), pa.array(out, pa.string())], ["doc_id", "shard", "text"])

    sharded = regions.df.withColumn("shard", shard)
    held = materialize(sharded.select("doc_id", "first", "shard").join(confirmed.df, ["doc_id", "first"]).groupBy("shard").agg(F.ceil(F.sum(F.size("offsets")) / (2 * SHARD_WINDOWS)).cast("int").alias("parts")), "held")
    streamed = sharded.groupBy("shard").agg(F.ceil(F.count(F.lit(1)) / STREAM_REGIONS).cast("int").alias("copies"))
    loads = streamed.join(held.df, "shard")  # shards without a passage need no stream
    passages = sharded.join(confirmed.df, ["doc_id", "first"]).select("doc_id", "shard", "region", "offsets").mapInArrow(cut_passages, "doc_id long, shard int, text string")
    deal = lambda rows, part, copy: rows.join(loads, "shard").withColumn("part", part).withColumn("copy", copy)
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    phrases = deal(passages, F.pmod(F.xxhash64("text"), F.col("parts")).cast("int"), each("copies"))
    targets = deal(sharded.withColumnRenamed("region", "text"), each("parts"), F.pmod(F.xxhash64("doc_id", "first"), "copies").cast("int"))
    columns = ["shard", "part", "copy", "kind", "doc_id", "text"]
    lanes = phrases.withColumn("kind", F.lit(0)).select(columns).unionByName(targets.withColumn("kind", F.lit(1)).select(columns))

    def stream(batches):
        lane, automaton, ready = None, None, False
        for batch in batches:
            keys, sources, later, own = [], [], [], []
            for *own_lane, kind, doc, text in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if own_lane != lane:
                    lane, automaton, ready = own_lane, Automaton(window), False
                if not kind:
                    automaton.add(doc, text)
                    continue
                if not ready:
                    automaton.compile()
                    ready = True
                if found := automaton.find(text):
                    keys.append(xxhash.xxh3_128_digest(text.encode()))
                    sources.append(doc)
                    later.append(np.array(merged([(a, b) for a, b, _ in found]), dtype=np.int64).ravel())
                    own.append(np.array(merged([(a, b) for a, b, source in found if source < doc]), dtype=np.int64).ravel())
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(sources, pa.int64()), _lists(later), _lists(own)], ["region", "source", "later", "own"])

    lanes = lanes.repartition("shard", "part", "copy").sortWithinPartitions("shard", "part", "copy", "kind", "doc_id")
    hits = materialize(lanes.mapInArrow(stream, "region binary, source long, later array<long>, own array<long>"), "hits")
    # In a region's earliest document only what stands earlier still is covered, in all others all that recurs.
    keyed = suspects.df.mapInArrow(cut_regions(False), f"{places}, region binary")
    edges = F.when(F.col("doc_id") == F.col("source"), F.col("own")).otherwise(F.col("later"))
    spans = keyed.join(hits.df, "region").select("doc_id", F.transform(edges, lambda x: x + F.col("first")).alias("edges")).where("size(edges) > 0")
    spans = materialize(spans.groupBy("doc_id").agg(F.flatten(F.collect_list("edges")).alias("edges")), "spans")
    whole = (
        scanned.df.select("doc_id", "n_words", "whole_sha256", "key").join(originals.df, "key")
        .select("doc_id", "n_words", "whole_sha256", (F.col("doc_id") > F.col("original")).alias("copy"))
    )
    for used in (recurring, flagged, regions, confirmed, held, hits):
        used.drop()
    return whole, spans.df, suspects.df


def _pairs(edges: list[int]) -> list[tuple[int, int]]:
    return merged(list(zip(edges[::2], edges[1::2])))


def remove_repeats(docs: DataFrame, window: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n_words, n_removed, kept_sha256)``: what is left of each text without the words ``repeated_spans`` covers."""
    whole, spans, suspects = repeated_spans(docs, window, id_col, text_col)

    def keep(batches):
        for batch in batches:
            removed, shas = [], []
            for raw, edges in zip(_raw(batch.column(1)), batch.column(2).to_pylist()):
                words, left, at, gone = raw.split(b" "), [], 0, 0
                for a, b in _pairs(edges):
                    left += words[at:a]
                    at, gone = b, gone + b - a
                left += words[at:]
                removed.append(gone)
                shas.append(hashlib.sha256(b" ".join(left)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(removed, pa.int64()), pa.array(shas, pa.string())], ["doc_id", "gone", "sha"])

    cut = suspects.select("doc_id", "words").join(spans, "doc_id").mapInArrow(keep, "doc_id long, gone long, sha string").dropDuplicates(["doc_id"])
    whole_copy = F.col("copy") & (F.col("n_words") >= window)
    return whole.join(cut, "doc_id", "left").select(
        "doc_id",
        "n_words",
        F.when(whole_copy, F.col("n_words")).otherwise(F.coalesce("gone", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole_copy, F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("sha", "whole_sha256")).alias("kept_sha256"),
    )


def without_repeats(docs: DataFrame, window: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with covered words cut out of ``text``; the white space between the words kept stays as it was.

    All columns stay, ``n_chars`` (if there) follows the text; a document whose every word is covered keeps its row with
    an empty text. Rows with a null id or text pass unchanged.
    """
    whole, spans, _ = repeated_spans(docs, window, id_col, text_col)
    copies = whole.where(F.col("copy") & (F.col("n_words") >= window)).select("doc_id", F.lit(True).alias("all")).distinct()
    marks = copies.join(spans, "doc_id", "full").select(F.col("doc_id").alias("_repeat_doc"), F.struct("all", "edges").alias("_repeat_mark"))
    return _rewrite(docs, marks, id_col, text_col)


def _rewrite(docs: DataFrame, marks: DataFrame, id_col: str, text_col: str) -> DataFrame:
    @F.pandas_udf("string")
    def cut(text: pd.Series, whole: pd.Series, edges: pd.Series) -> pd.Series:
        out = []
        for t, gone, e in zip(text, whole, edges):
            if t is None or (gone is not True and e is None):
                out.append(t)
                continue
            if gone is True:
                out.append("")
                continue
            raw = t.encode()
            places = [m.span() for m in _WORD.finditer(raw)]
            left, at = [], 0
            for a, b in _pairs(e):
                if a >= len(places):
                    break
                left.append(raw[at : places[a][0]])
                at = places[b][0] if b < len(places) else len(raw)
            left.append(raw[at:])
            out.append(b"".join(left).decode())
        return pd.Series(out, dtype=object)

    joined = docs.join(marks, docs[id_col] == marks["_repeat_doc"], "left")
    mark = F.col("_repeat_mark")
    out = joined.withColumn(text_col, cut(text_col, mark["all"], mark["edges"]))
    if "n_chars" in docs.columns:
        counted = F.length(text_col).cast(docs.schema["n_chars"].dataType)
        out = out.withColumn("n_chars", F.when(F.col("_repeat_doc").isNotNull(), counted).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)
