"""Each operation against brute force, closed forms, round trips or held-out accuracy, and on awkward tables."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib
from fractions import Fraction

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from tidegraph.llm import decontam, htmltext, licenses, mixing, phrases, quality, queries, rollup, simhash, telephony, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, texts, ids=None):
    return spark.createDataFrame([(i, t, "en", f"s{k % 2}", None if t is None else len(t)) for k, (i, t) in enumerate(zip(ids or range(len(texts)), texts))], SCHEMA)


def words_of(n, seed, vocabulary=5000):
    r = random.Random(seed)
    return [f"w{r.randrange(vocabulary)}" for _ in range(n)]


@pytest.fixture(scope="module")
def tables(spark, sf):
    return {t: spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels", "pages", "benchmark")}


@pytest.fixture(scope="module")
def awkward(spark):
    """Nulls in every column, empty and long texts, ties, a repeated row, and columns named like internal ones."""
    long = " ".join(words_of(30_000, 1))
    rows = [(0, None, None, None, None), (1, "", "en", "s0", 0), (2, "   \n", "en", "s0", 4), (3, "x", "en", "s0", 1), (4, long, "en", "s1", len(long)), (5, long, "en", "s1", len(long)), (5, long, "en", "s1", len(long)), (None, "no id", None, None, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    for name in ("id", "fp", "key", "edges", "slot", "label", "words", "score", "shard", "w"):
        df = df.withColumn(name, F.lit(name))
    return df


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# 1. toxicity
def brute_segments(scores):
    """Maximal scoring segments by their definition: the best segment, the shortest of ties, then those left and right of it."""
    best = max(((sum(scores[i:j]), i - j, -i) for i in range(len(scores)) for j in range(i + 1, len(scores) + 1)), default=(0, 0, 0))
    if best[0] <= 0:
        return []
    i, j = -best[2], -best[2] - best[1]
    return brute_segments(scores[:i]) + [(i, j - 1, best[0])] + [(a + j, b + j, s) for a, b, s in brute_segments(scores[j:])]


def test_segments_are_the_maximal_ones():
    r = random.Random(2)
    for _ in range(200):
        scores = [r.choice([-1.0, -1.0, -1.0, 0.75, 1.5, 2.25, -2.5]) for _ in range(18)]
        places = [i for i, s in enumerate(scores) if s != -1.0]
        got = toxicity.maximal_segments([scores[i] for i in places], places, 1.0)
        assert [(a, b, round(s, 6)) for a, b, s in got] == [(a, b, round(s, 6)) for a, b, s in brute_segments(scores)]


def test_toxicity_separates(spark):
    texts, labels = [], []
    for i in range(300):
        w = words_of(60, i, 300)
        if i % 3 == 0:
            for k in range(4):
                w[k * 9] = "vile"
        texts.append(" ".join(w))
        labels.append((i, int(i % 3 == 0)))
    docs, marks = docs_of(spark, texts), spark.createDataFrame(labels, "doc_id long, toxic int")
    rows = toxicity.score(docs, toxicity.fit(docs, marks)).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    assert all(r.predicted == int(r.doc_id % 3 == 0) for r in rows) and all(0 <= r.score <= 1 for r in rows)
    left = {r.doc_id for r in toxicity.without_toxic(docs, marks).collect()}
    assert left == {i for i in range(300) if i % 3}


def test_toxicity_on_awkward_tables(spark, awkward, empty, tables):
    model = toxicity.fit(tables["documents"], tables["labels"])
    assert toxicity.score(awkward, model).count() == awkward.count() and toxicity.score(empty, model).count() == 0
    none = toxicity.fit(empty, tables["labels"])
    assert {r.score for r in toxicity.score(awkward, none).collect()} == {0.5}
    assert toxicity.without_toxic(awkward, tables["labels"]).columns == awkward.columns


# 2. substring dedup
def brute_repeats(texts, window=50):
    first, words = {}, {}
    for i in sorted(texts):
        words[i] = (texts[i] or "").encode().split()
        for p in range(len(words[i]) - window + 1):
            first.setdefault(tuple(words[i][p : p + window]), i)
    out = {}
    for i, w in words.items():
        gone = [False] * len(w)
        for p in range(len(w) - window + 1):
            if first[tuple(w[p : p + window])] < i:
                gone[p : p + window] = [True] * window
        kept = [x for x, g in zip(w, gone) if not g]
        out[i] = (len(w), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


def repeated_texts():
    passage, other = words_of(140, 50), words_of(60, 51)
    texts = {}
    for i in range(24):
        w = words_of(80, 100 + i)
        if i % 3 == 0:
            w[20:20] = passage[i : i + 55 + i]
        if i % 4 == 0:
            w += other
        if i % 5 == 0:
            w[5:5] = other[:49]
        texts[i] = " \t".join(w[:40]) + "\n" + " ".join(w[40:])
    texts[24], texts[25], texts[26], texts[27] = texts[3], " ".join(["a"] * 130), " ".join(["a"] * 60), None
    texts[28] = " ".join(words_of(70, 9)) + " é" * 55
    texts[29] = texts[28] + " tail"
    return texts


def test_repeats_match_brute_force(spark):
    texts = repeated_texts()
    docs = docs_of(spark, list(texts.values()), list(texts))
    want = brute_repeats(texts)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in phrases.remove_repeats(docs).collect()}
    assert got == want and sum(x[1] for x in want.values()) > 400
    cut = {r.doc_id: r for r in phrases.without_repeats(docs).collect()}
    assert {i: hashlib.sha256(b" ".join((r.text or "").encode().split())).hexdigest() for i, r in cut.items()} == {i: x[2] for i, x in want.items()}
    assert all(r.text is None or r.n_chars == len(r.text) for r in cut.values())


def test_repeats_over_several_automata_of_a_shard(spark, monkeypatch):
    """With small automata and streams a shard has several of each; the result is the same."""
    monkeypatch.setattr(phrases, "SHARD_WINDOWS", 8)
    monkeypatch.setattr(phrases, "STREAM_REGIONS", 3)
    texts = repeated_texts()
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in phrases.remove_repeats(docs_of(spark, list(texts.values()), list(texts))).collect()}
    assert got == brute_repeats(texts)


def test_repeats_of_the_documents_match_brute_force(spark, tables):
    texts = {r.doc_id: r.text for r in tables["documents"].collect()}
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in phrases.remove_repeats(tables["documents"]).collect()}
    assert got == brute_repeats(texts)


def test_repeats_on_awkward_tables(spark, awkward, empty):
    got = sorted((r.doc_id, r.n_words, r.n_removed) for r in phrases.remove_repeats(awkward).collect())
    assert got == [(0, 0, 0), (1, 0, 0), (2, 0, 0), (3, 1, 0), (4, 30000, 0), (5, 30000, 30000), (5, 30000, 30000)]
    out = phrases.without_repeats(awkward)
    assert out.columns == awkward.columns and out.count() == awkward.count()
    assert phrases.remove_repeats(empty).count() == 0 and phrases.without_repeats(empty).count() == 0


# 3. token rollups
def test_rollup_is_additive_and_idempotent(spark, tables):
    docs = tables["documents"]
    store = rollup.RollupStore(spark)
    inserted = docs.withColumn("sign", F.lit(1))
    assert store.commit("b1", inserted) and not store.commit("b1", inserted)
    tokens = rollup.counter("byte_bpe_50k.tiktoken")
    want = collections.Counter()
    for r in docs.collect():
        for name, n in (("words", len(r.text.encode().split())), ("byte_bpe_50k.tiktoken", tokens([r.text])[0])):
            for k, v in (("n_docs", 1), ("n_chars", len(r.text)), ("n_tokens", n)):
                want[r.source, r.lang, name, k] += v
    read = lambda: {(r.source, r.lang, r.tokenizer, k): r[k] for r in store.totals().collect() for k in rollup.MEASURES}
    assert read() == dict(want)
    changed = docs.where("doc_id < 5").withColumn("text", F.concat("text", F.lit(" more words")))
    assert store.commit("b2", rollup.revisions(docs.where("doc_id < 5"), changed))
    assert sum(v for k, v in read().items() if k[2] == "words" and k[3] == "n_tokens") == sum(v for k, v in want.items() if k[2] == "words" and k[3] == "n_tokens") + 10
    store.compact()
    before = read()
    assert not store.commit("b1", inserted) and store.committed() == {"b1", "b2"} and read() == before
    store.commit("b3", rollup.revisions(changed, docs.where("doc_id < 5")))
    store.compact()
    assert read() == dict(want)
    store.commit("b4", docs.withColumn("sign", F.lit(-1)))
    assert store.totals().count() == 0


def test_rollup_on_awkward_tables(spark, awkward, empty):
    store = rollup.RollupStore(spark)
    assert store.totals().count() == 0
    store.commit("e", empty.withColumn("sign", F.lit(1)))
    assert store.totals().count() == 0
    store.commit("a", awkward.withColumn("sign", F.lit(None).cast("int")), ("words",))
    rows = store.totals().collect()
    assert sum(r.n_docs for r in rows) == 8 and any(r.source is None for r in rows)
    with pytest.raises(ValueError):
        store.commit("../x", empty)


def test_other_tokenizers_count(spark):
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model", "byte_bpe_multi_50k.tiktoken"):
        assert rollup.counter(name)(["hello world", ""])[0] >= 2


# 4. decontamination
def test_leaks_are_found_and_reparameterised_ones_too(spark):
    item = "A farmer named Alice has 12 apples and gives 5 kg of them to Bob who keeps 12 for the long winter ahead"
    other = item.replace("12", "37").replace("Alice", "Grace").replace("kg", "lbs").replace("5", "6")
    broken = item.replace("keeps 12", "keeps 99")
    filler = " ".join(words_of(40, 3))
    docs = docs_of(spark, [f"{filler} {item} {filler}", f"{filler}\n{other.upper()}!! {filler}", f"{filler} {broken}", filler, None, "", item[:60]])
    bench = spark.createDataFrame([(7, item), (8, "short one here"), (9, None), (10, "")], "item_id long, text string")
    got = {(r.doc_id, r.item_id): r for r in decontam.matches(docs, bench, least=0.8).collect()}
    assert {k for k in got} == {(0, 7), (1, 7)}
    assert got[0, 7].n_exact == got[0, 7].n_windows and got[1, 7].n_exact < got[1, 7].n_matched == got[1, 7].n_windows
    assert got[0, 7].coverage == 1.0
    assert {r.doc_id for r in decontam.without_leaks(docs, bench, least=0.8).collect()} == {2, 3, 4, 5, 6}
    short = docs_of(spark, ["we saw a short one here today", "a short other one here"])
    assert {(r.doc_id, r.item_id) for r in decontam.matches(short, bench).collect()} == {(0, 8)}


def test_values_outside_all_lists_are_slots(spark):
    """Names by their capitals, number words, glued units; two values may fall together, one may not fall apart."""
    item = "After the long winter Alberto of Toronto sold 12 crates at 5km from home and later Alberto gave 5 of them to three neighbours near the river Elbe"
    asked = "After the long winter Priya of Madrid sold 6 crates at 6ft from home and later Priya gave 6 of them to nine neighbours near the river Tagus"
    apart = asked.replace("later Priya", "later Ingrid")
    lower, filler = item.lower(), " ".join(words_of(30, 4))
    texts = [f"{filler}. {x} {filler}" for x in (item, asked, apart, lower)] + [filler]
    got = {r.doc_id: r for r in decontam.matches(docs_of(spark, texts), spark.createDataFrame([(1, item), (1, "another text of the same number that stands nowhere at all"), (2, None)], "item_id long, text string"), least=0.9).collect()}
    assert sorted(got) == [0, 1, 3] and [got[i].coverage for i in (0, 1, 3)] == [1.0, 1.0, 1.0]
    assert got[0].n_exact == got[3].n_exact == got[0].n_windows and got[1].n_exact < got[1].n_windows


def test_leaks_match_brute_force(spark, tables):
    width = decontam.WINDOW
    split = lambda t: [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub(r"(?<=[0-9])[.,](?=[0-9])", "", (t or "").lower())) if w]
    items = {r.item_id: split(r.text) for r in tables["benchmark"].collect()}
    docs = {r.doc_id: split(r.text) for r in tables["documents"].collect()}
    want = set()
    for d, w in docs.items():
        grams = {tuple(w[i : i + width]) for i in range(len(w) - width + 1)}
        for k, v in items.items():
            own = [tuple(v[i : i + width]) for i in range(len(v) - width + 1)]
            if own and sum(g in grams for g in own) >= 0.5 * len(own):
                want.add((d, k))
    assert {(r.doc_id, r.item_id) for r in decontam.matches(tables["documents"], tables["benchmark"]).collect()} == want and want


def test_leaks_on_awkward_tables(spark, awkward, empty, tables):
    assert decontam.matches(empty, tables["benchmark"]).count() == 0 and decontam.matches(awkward, empty.select(F.col("doc_id").alias("item_id"), "text")).count() == 0
    out = decontam.without_leaks(awkward, tables["benchmark"])
    assert out.columns == awkward.columns and out.count() == awkward.count()


# 5. telephony audio
def test_law_tables():
    mu, a = telephony.mulaw_table(), telephony.alaw_table()
    assert mu[0xFF] == 0 and mu[0x7F] == 0 and mu[0x00] == -32124 and mu[0x80] == 32124 and len(set(mu.tolist())) == 255
    assert a[0xD5] == 8 and a[0x55] == -8 and a[0x2A] == -32256 and a[0xAA] == 32256


def test_adpcm_blocks_match_a_sample_loop():
    r = np.random.default_rng(4)
    blocks = r.integers(0, 256, (7, 36), dtype=np.uint8)
    steps, moves = telephony.adpcm_steps().tolist(), [-1, -1, -1, -1, 2, 4, 6, 8] * 2
    want = []
    for b in blocks:
        value, index = int.from_bytes(bytes(b[:2]), "little", signed=True), min(int(b[2]), 88)
        out = [value]
        for byte in b[4:]:
            for n in (int(byte) & 15, int(byte) >> 4):
                s = steps[index]
                d = (s >> 3) + (s if n & 4 else 0) + (s >> 1 if n & 2 else 0) + (s >> 2 if n & 1 else 0)
                value = max(-32768, min(32767, value - d if n & 8 else value + d))
                index = max(0, min(88, index + moves[n]))
                out.append(value)
        want.append(out)
    assert telephony.decode_adpcm(blocks).tolist() == want


def test_stored_texts_round_trip(spark, tables):
    texts = {r.doc_id: (r.text or "").encode() for r in tables["documents"].collect()}
    for r in telephony.store_texts(tables["documents"]).collect():
        raw = texts[r.doc_id]
        payload = raw + b"\xff" * (max(1, -(-len(raw) // 576)) * 576 - len(raw))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]))
        media = telephony.container(telephony.MULAW, 8000, 8, 1, payload)
        assert (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest()) and telephony.parts(media)[3] == payload


def test_media_column_and_awkward_tables(spark, awkward, empty):
    rows = telephony.store_texts(awkward).collect()
    assert len(rows) == 8 and len({r.feature for r in rows if r.payload_bytes > 1000}) == 1
    assert telephony.store_texts(empty).count() == 0
    mu = telephony.container(telephony.MULAW, 8000, 8, 1, bytes(range(256)))
    ad = telephony.container(telephony.ADPCM, 8000, 4, 36, bytes(72))
    df = spark.createDataFrame([(1, bytearray(mu)), (2, bytearray(ad)), (3, None), (4, bytearray(b"noise"))], "id long, media binary")
    got = {r.id: r.pcm for r in telephony.decode_column(df).collect()}
    assert got[3] is None and got[4] is None
    rate, samples = telephony.decode(bytes(got[1]))
    assert rate == 16000 and samples[::2].tolist() == telephony.mulaw_table().tolist() and len(telephony.decode(bytes(got[2]))[1]) == 2 * 2 * 65


# 6. mixing
def furthest(taken, weights):
    """How far a source gets from its share, over all slots until one has no block left."""
    total, until = sum(Fraction(w) for w in weights.values()), min(x[-1] for x in taken.values())
    worst = 0.0
    for s, x in taken.items():
        share = float(Fraction(weights[s]) / total)
        own, i = x[x <= until], np.arange(np.count_nonzero(x <= until))
        # The count jumps from i to i + 1 over the slot own[i]: furthest ahead just after it, furthest behind just before it.
        worst = max(worst, (i + 1 - share * (own + 1)).max(initial=0), (share * own - i).max(initial=0), share * (until + 1) - len(own))
    return worst


def test_schedule_keeps_within_a_block():
    cases = [{"a": 5.0, "b": 3.0, "c": 1.0, "d": 0.2}, {"a": 0.618, "b": 0.300, "c": 0.082}, {"a": 10000, "b": 3000, "c": 2}, {f"e{k}": 1.0 for k in range(7)}, {f"r{k}": (k + 2) ** 0.5 for k in range(6)}]
    for weights in cases:
        total = sum(weights.values())
        taken = mixing.plan({s: int(300_000 * w / total) + 5 for s, w in weights.items()}, weights)
        assert sorted(np.concatenate(list(taken.values())).tolist()) == list(range(sum(map(len, taken.values()))))
        assert furthest(taken, weights) < 1


def test_schedule_of_a_million_slots_and_a_thousand_sources():
    weights = {f"s{k}": random.Random(k).random() ** 3 + 1e-4 for k in range(1000)}
    total = sum(weights.values())
    taken = mixing.plan({s: int(1_000_000 * w / total) + 3 for s, w in weights.items()}, weights)
    assert furthest(taken, weights) < 1 and len(np.unique(np.concatenate(list(taken.values())))) == sum(map(len, taken.values()))


def test_mixed_documents_are_whole_and_fair(spark):
    rows = [(i, "x", "en", "hot" if i % 3 else f"s{i % 4}", 1) for i in range(3000)]
    docs = spark.createDataFrame(rows, SCHEMA)
    weights = {"hot": 1.0, "s0": 1.0, "s1": 2.0, "s2": 1.0, "s3": 1.0}
    out = mixing.scheduled(docs, weights, block_rows=10).collect()
    assert sorted(r.doc_id for r in out) == list(range(3000))
    by_slot = collections.defaultdict(list)
    for r in out:
        by_slot[r.slot].append(r)
    assert sorted(by_slot) == list(range(len(by_slot))) and all(len({x.source for x in v}) == 1 and len(v) <= 10 for v in by_slot.values())
    assert all(sorted(x.row_in_block for x in v) == list(range(len(v))) for v in by_slot.values())
    done = collections.Counter()
    left = collections.Counter({s: sum(1 for v in by_slot.values() if v[0].source == s) for s in weights})
    for t in range(len(by_slot)):
        done[by_slot[t][0].source] += 1
        if any(done[s] == left[s] for s in weights):
            break
        assert all(abs(done[s] - weights[s] / 6 * (t + 1)) < 1 for s in weights)
    ordered = [r.slot for r in mixing.in_mixed_order(mixing.scheduled(docs, weights)).collect()]
    assert ordered == sorted(ordered)


def test_mixing_awkward_tables(spark, awkward, empty):
    out = mixing.scheduled(awkward)
    assert out.count() == 8 and out.columns == [c for c in awkward.columns if c != "slot"] + ["block", "slot", "row_in_block"]
    assert mixing.scheduled(empty).count() == 0


# 7. SimHash
def brute_fingerprint(text, width=3):
    w = re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()).split()
    s = [b" ".join(w[i : i + width]) for i in range(len(w) - width + 1)] if len(w) >= width else ([b" ".join(w)] if w else [])
    hashes = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if s and 2 * sum(h >> b & 1 for h in hashes) > len(s))


def brute_components(prints, distance):
    up = {i: i for i in prints}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(prints), 2):
        if (prints[a] ^ prints[b]).bit_count() <= distance:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    return {i: root(i) for i in prints}


def test_components_match_brute_force(spark, tables):
    prints = {r.doc_id: brute_fingerprint(r.text) for r in tables["documents"].collect()}
    want = brute_components(prints, 3)
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_components(tables["documents"]).collect()} == {i: (f"{prints[i]:016x}", want[i]) for i in prints}


@pytest.mark.parametrize("distance", [3, 5])
def test_links_over_dense_groups(spark, distance, monkeypatch):
    """Groups beyond a block connect as in brute force, without all their pairs."""
    monkeypatch.setattr(simhash, "BLOCK", 16)
    r = random.Random(distance)
    centres = [r.getrandbits(64) for _ in range(4)]
    prints = {}
    for i in range(150):
        x = r.choice(centres)
        for b in r.sample(range(64), r.randrange(0, 6)):
            x ^= 1 << b
        prints[i] = x
    nodes = spark.createDataFrame([(i, x - (1 << 64) if x >> 63 else x) for i, x in prints.items()], "id long, fp long")
    links = [(r.a, r.b) for r in simhash.near_links(nodes, distance).df.collect()]
    assert len(links) < 20 * len(prints)
    up = {i: i for i in prints}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    assert {i: root(i) for i in prints} == brute_components(prints, distance)


def test_near_duplicates_match_brute_force(spark):
    texts = []
    for i in range(12):
        w = words_of(120, i, 4000)
        texts.append(" ".join(w))
        for k in range(i % 4):
            v = list(w)
            for j in random.Random(i * 10 + k).sample(range(120), 1 + k % 2):
                v[j] = "edited"
            texts.append(" ".join(v).upper())
    docs = docs_of(spark, texts)
    sets = [set(zip(*(t.lower().split()[i:] for i in range(5)))) for t in texts]
    up = list(range(len(texts)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(range(len(texts)), 2):
        if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    assert {r.doc_id: r.group_id for r in simhash.near_duplicate_groups(docs).collect()} == {i: root(i) for i in range(len(texts))}


def test_inserted_and_dropped_blocks_are_near_duplicates(spark):
    """Appended, truncated and scattered-edit pairs near 0.8: none that brute force has is missed, none is added."""
    texts = []
    for i in range(40):
        w = words_of(200, 900 + i, 4000)
        scattered = list(w)
        for j in random.Random(i).sample(range(200), 4):
            scattered[j] = "edited"
        texts += [" ".join(v) for v in (w, w + words_of(36 + i // 2, 2000 + i, 4000), w[: 172 - i // 2], scattered)]
    sets = [set(zip(*(t.split()[k:] for k in range(5)))) for t in texts]
    up = list(range(len(texts)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    near = [(a, b) for a, b in itertools.combinations(range(len(texts)), 2) if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    assert min(collections.Counter((b - a, a % 4) for a, b in near)[k] for k in ((1, 0), (2, 0), (3, 0))) > 20
    for a, b in near:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    assert {r.doc_id: r.group_id for r in simhash.near_duplicate_groups(docs_of(spark, texts)).collect()} == {i: root(i) for i in range(len(texts))}


def test_near_copies_of_the_documents_are_all_found(spark, tables):
    """All documents against all: every pair at 0.8 or more is in one group, those of ids that 20 divides among them."""
    rows = {r.doc_id: (r.text or "").encode().lower().split() for r in tables["documents"].collect()}
    sets = {i: set(simhash.shingles(w, 5)) for i, w in rows.items() if w}
    group = {r.doc_id: r.group_id for r in simhash.near_duplicate_groups(tables["documents"]).collect()}
    alike = lambda x, y: 5 * min(len(x), len(y)) >= 4 * max(len(x), len(y)) and 5 * len(x & y) >= 4 * len(x | y)
    pairs = [(i, j) for i, j in itertools.combinations(sorted(sets), 2) if alike(sets[i], sets[j])]
    assert any(i % 20 == 0 or j % 20 == 0 for i, j in pairs) and all(group[i] == group[j] for i, j in pairs)


def test_simhash_on_awkward_tables(spark, awkward, empty):
    got = sorted((r.doc_id, r.component_id) for r in simhash.near_components(awkward).collect())
    assert got == [(0, 0), (1, 0), (2, 0), (3, 3), (4, 4), (5, 4), (5, 4)]
    groups = sorted((r.doc_id, r.group_id) for r in simhash.near_duplicate_groups(awkward).collect())
    assert groups == [(0, 0), (1, 1), (2, 2), (3, 3), (4, 4), (5, 4), (5, 4)]
    assert simhash.near_components(empty).count() == 0 and simhash.near_duplicate_groups(empty).count() == 0


# 8. page text
PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href="/a">A</a></li></ul></nav><div class="ad">Buy now</div><div class="cookie-notice">We use cookies</div>
<article><h1>Of &amp; on&nbsp;it</h1><p><b>First
 part.<br><p>Second <i>one</i>&#33;</p><form><input name=q><button>Go</button></form><div class="share">Share</div><ul><li>Item</ul><p>Eron.</p>
<section class="comments"><p>Nice article, I liked it very much indeed!</p></section></article><aside>More</aside><footer>&copy; me</footer></body></html>"""


def test_page_text():
    assert htmltext.main_text(PAGE) == "Of & on it\nFirst part.\nSecond one!\nItem\nEron."
    assert htmltext.main_text(PAGE.split("<section")[0]) == "Of & on it\nFirst part.\nSecond one!\nItem\nEron."
    bare = "<body><div id=nav><a href=1>x</a></div><div>" + "".join(f"<p>{' '.join(words_of(40, i))}</p>" for i in range(4)) + "</div></body>"
    assert htmltext.main_text(bare) == "\n".join(" ".join(words_of(40, i)) for i in range(4))
    assert htmltext.main_text(None) == htmltext.main_text("") == htmltext.main_text("<p></p>") == htmltext.main_text("<nav>x</nav>") == ""


def test_page_text_of_several_regions():
    """Text in a div beside a teaser card, and in sibling articles; the card is no content."""
    blocks = [" ".join(words_of(40, 70 + i)) for i in range(6)]
    body = "".join(f"<p>{x}</p>" for x in blocks[:3])
    card = "<article><h2><a href=1>More</a></h2><p><a href=2>Read it</a></p></article>"
    assert htmltext.main_text(f"<body>{card}<div>{body}</div>{card}</body>") == "\n".join(blocks[:3])
    two = f"<body><article>{body}</article><article><h2>Part two</h2>" + "".join(f"<p>{x}</p>" for x in blocks[4:]) + "</article></body>"
    assert htmltext.main_text(two) == "\n".join([*blocks[:3], "Part two", *blocks[4:]])


def test_pages_of_the_table(spark, tables):
    import html

    rows = {r.page_id: r for r in htmltext.extract_pages(tables["pages"]).collect()}
    for p in tables["pages"].collect():
        article = re.search(r"<article>(.*?)(?:</article>|<footer>|$)", p.html, re.S)[1]
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]*>", "", x)).split()) for x in re.split(r"</?(?:p|h1)>", article)]
        assert rows[p.page_id].text == "\n".join(b for b in blocks if b) and rows[p.page_id].n_chars == len(rows[p.page_id].text)


def test_pages_awkward(spark):
    df = spark.createDataFrame([(1, None, None, "t"), (None, "u", "<article><p>x", "t"), (2, "u", "", "t")], "page_id long, url string, html string, text string")
    assert sorted((r.page_id or 0, r.text) for r in htmltext.extract_pages(df).collect()) == [(0, "x"), (1, ""), (2, "")]
    assert htmltext.extract_pages(df.limit(0)).count() == 0


def test_pages_with_forms_several_articles_or_none():
    long = lambda k: f"Paragraph {k} goes on for long enough to stand out from menus, with a dozen more words behind it, so that it counts."
    shown = lambda body: htmltext.main_text(f"<html><body>{body}</body></html>").split("\n")
    nav = "<ul><li><a href=x>One</a></li><li><a href=y>Two</a></li><li><a href=z>Three</a></li></ul>"
    assert shown(f"<div>{nav}</div><div><p>{long(1)}</p><p>Short.</p><p>{long(2)}</p></div><div>{nav}</div>") == [long(1), "Short.", long(2)]
    assert shown(f"<article><p>{long(1)}</p></article><article><p>{long(2)}</p><p>Tail.</p></article>") == [long(1), long(2), "Tail."]
    assert shown(f"<form action=/><div>{nav}</div><article><p>{long(1)}</p></article></form>") == [long(1)]
    assert shown(f"<form><p>{long(1)}</p><p>{long(2)}</p></form>") == [long(1), long(2)]
    assert shown(f"<article><p>{long(1)}</p><form><p>Your mail address, please</p><input><button>Send</button></form></article>") == [long(1)]
    assert shown(f"<article><p>{long(1)}</p><p><script>{'<b>' * 9}</script>Next one here</p></article>") == [long(1), "Next one here"]


def test_deep_and_long_pages_end():
    deep = "<div><span>" * 3_000 + "core " * 200 + "</i></b>" * 20_000
    assert htmltext.main_text(f"<article>{deep}</article>").split()[:2] == ["core", "core"]
    assert htmltext.main_text("<p>a b c d e f g h</p>" * 20_000).count("\n") == 19_999


# 9. licenses
def brute_scan(text):
    words = [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub(r"[A-Z]", lambda m: m[0].lower(), text or "")) if w]
    places = {k: [i for i in range(len(words)) if tuple(words[i : i + len(p)]) == p] for k, p in licenses.PHRASES.items()}
    found = sorted(itertools.chain(*places.values()))
    return len(words), len(found), found[0] if found else None, found[-1] if found else None, ",".join(sorted(k for k, v in places.items() if v))


def test_license_scan_matches_brute_force(spark, tables):
    whole = licenses.TEMPLATES["mit"][0].split()
    wrapped = ["\n".join("# " + " ".join(whole[i : i + 9]) for i in range(0, len(whole), 9)), " ".join(whole[:40] + ["other"] * 100 + whole[40:])]
    bsd = "Redistribution and use in source and binary forms, with or without\n * modification, are permitted provided that the following\n * conditions are met:"
    extra = ["MIT License and mit-license, the Apache  License; general public\nlicense", "mit licenses", "M\u0130T License \u212aelvin", "released the license under mit", "Licensed under CC BY-NC 4.0. x", "Licensed\nunder CC\nBY-NC 4.0", "license", None, "", bsd, *wrapped]
    docs = tables["documents"].select("doc_id", "text").unionByName(spark.createDataFrame([(10_000 + i, t) for i, t in enumerate(extra)], "doc_id long, text string"))
    rows = {r.doc_id: r for r in licenses.scan(docs).collect()}
    templates = {k: [licenses.template_words(t) for t in v] for k, v in licenses.TEMPLATES.items()}
    for d in docs.collect():
        r = rows[d.doc_id]
        n, base, first, last, labels = brute_scan(d.text)
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (n, base, first, last, labels)
        words, best = licenses.template_words(d.text or ""), {}
        for k, ts in templates.items():
            for t in ts:
                span, own = licenses.span_of(t, 0.8), set(t)
                if len(own & set(words)) >= licenses.least_of(t, 0.8):
                    held = max(len(own & set(words[i : i + span])) / len(own) for i in range(len(words)))
                    best[k] = max(best.get(k, 0), held)
        good = {k: v for k, v in best.items() if v >= 0.8}
        assert r.labels == ",".join(sorted(set(good) | set(filter(None, labels.split(",")))))
        assert r.score == (1.0 if base else max(good.values(), default=0.0))
    assert rows[10_000 + extra.index(bsd)].labels == "bsd" and rows[10_000 + len(extra) - 2].labels == "mit" and rows[10_000 + len(extra) - 1].labels == ""


def test_license_scan_awkward(spark, awkward, empty):
    assert licenses.scan(awkward).count() == 7 and licenses.scan(empty).count() == 0


# 10. quality
def test_rules_and_columns_agree(spark, tables):
    model = quality.fit(tables["documents"], tables["labels"])
    stats = tables["documents"].select("doc_id", *[c.alias(n) for n, c in quality.statistics().items()]).orderBy("doc_id").toPandas()
    names = list(quality.statistics())
    x = stats[names].to_numpy(dtype=float)
    z = model.intercept + sum(r.weight * r.holds(x, names) for r in model.rules)
    rows = {r.doc_id: r for r in quality.score(tables["documents"], model).collect()}
    assert all(math.isclose(rows[i].score, 1 / (1 + math.exp(-v)), abs_tol=1e-9) for i, v in zip(stats["doc_id"], np.atleast_1d(z) + np.zeros(len(x))))
    assert all(r.predicted == int(r.score >= 0.7) and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows.values())


def test_quality_separates_and_awkward(spark, tables, awkward, empty):
    texts = [" ".join(words_of(50, i)) if i % 2 else " ".join(w.upper() + "!!" for w in words_of(50, i)) for i in range(200)]
    docs, marks = docs_of(spark, texts), spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, quality int")
    model = quality.fit(docs, marks)
    assert all(r.predicted == r.doc_id % 2 for r in quality.score(docs, model).collect())
    rows = quality.score(awkward, model).collect()
    assert len(rows) == 8 and all(0 <= r.score <= 1 for r in rows) and quality.score(empty, model).count() == 0
    assert quality.fit(empty, marks).rules == []


@pytest.mark.parametrize("operation, label, least", [(toxicity, "toxic", 0.97), (quality, "quality", 0.97)])
def test_held_out_accuracy(spark, operation, label, least):
    """On the labelled rows that the fit never saw, over the largest table at hand."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    scored = operation.score(docs, operation.fit(docs, labels)).where("held_out").join(labels, "doc_id")
    right = scored.agg(F.avg((F.col("predicted") == F.col(label)).cast("double")).alias("right"), F.count(F.lit(1)).alias("n")).first()
    print(label, right)
    assert right.n > 500 and right.right >= least


# The pipeline
def test_pipeline_runs_its_stages(spark, sf, tables):
    import corpus_pipeline

    docs = tables["documents"]
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        if name != "mixing":
            assert out.columns == docs.columns
        docs = spark.createDataFrame(out.collect(), out.schema)
    rows = docs.collect()
    assert len({r.doc_id for r in rows}) == len(rows)
    leaked = {r.doc_id for r in decontam.matches(docs, tables["benchmark"]).collect()}
    assert not leaked
    assert len(simhash.near_duplicate_groups(docs.where("length(text) > 0")).select("group_id").distinct().collect()) == docs.where("length(trim(text)) > 0").count()


def test_pipeline_on_awkward_and_empty_tables(spark, tables, awkward, empty, tmp_path):
    """All stages in a row, as registered: rows without an id stay, texts that are equal word for word once."""
    import corpus_pipeline

    for name, docs in (("awkward", awkward), ("empty", empty)):
        folder = str(tmp_path / name)
        docs.write.parquet(f"{folder}/documents.parquet")
        for t in ("labels", "benchmark"):
            (tables[t] if name == "awkward" else tables[t].limit(0)).write.parquet(f"{folder}/{t}.parquet")
        out = corpus_pipeline.run(spark, folder)
        assert out.columns == [c for c in docs.columns if c != "slot"] + ["block", "slot", "row_in_block"]
        rows = out.collect()
        if name == "awkward":
            assert sorted((r.doc_id is None, r.doc_id) for r in rows if r.doc_id is not None) == [(False, i) for i in (0, 1, 2, 3, 4)] and sum(r.doc_id is None for r in rows) == 1
        else:
            assert not rows


def test_every_operation_has_a_query():
    assert [n.split("_")[0] for n in queries.QUERIES] == [f"op{k}" for k in range(1, 11)]
