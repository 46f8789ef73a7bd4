"""Toxicity by maximum-scoring segments.

Each word scores its log-odds between toxic and clean text under an informative Dirichlet prior, taken as zero where it
cannot be told from zero, less a drift, and one linear scan finds every maximal segment of a text. Segment scores are
judged against the extreme-value distribution of the best segment of clean text of the same length, whose rate and scale
are fitted to clean texts, and the text's probability is a logistic of what its segments show.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from tidegraph.llm.labels import fit_logistic, held_out, training_rows
from tidegraph.runtime import materialize, ship

_WORD = re.compile(r"[^\W\d_]+")
#: Letters of the stems that stand in for words the lexicon does not have.
STEM = 5

#: Bound of the fit: labelled documents used. All their words that lean are in the lexicon.
MAX_TRAINING_DOCS = 20_000
#: Lowest score of a word, so that no single word hides a passage.
LEAST_SCORE = -4.0


def words(text: str) -> list[str]:
    return _WORD.findall(text.lower())


@dataclass
class Model:
    """``lexicon`` scores words; ``stems`` score words it does not have by their first letters; all others score -``drift``."""

    lexicon: dict[str, float]
    stems: dict[str, float]
    drift: float
    rate: float  # of the extreme-value distribution, by which scores are scaled
    scale: float  # its K
    weights: list[float] = field(default_factory=lambda: [0.0, 1.0, 0.0, 0.0])  # intercept, best, together, share
    level: float = 0.01


def maximal_segments(scores: list[float], places: list[int], drift: float) -> list[tuple[int, int, float]]:
    """Every maximal scoring segment ``(first, last, score)`` of a sequence that scores ``scores`` at ``places`` and -drift elsewhere.

    One pass: each segment keeps the running totals before its first and after its last place, and a pointer to the last
    earlier segment that starts lower. A new positive place looks along these pointers and absorbs what it tops.
    """
    lows: list[float] = []
    highs: list[float] = []
    spans: list[tuple[int, int]] = []
    lower: list[int] = []
    total, at = 0.0, 0
    for place, score in zip(places, scores):
        total -= drift * (place - at)
        at = place + 1
        low, total = total, total + score
        if score <= 0:
            continue
        first, j = place, len(lows) - 1
        while True:
            while j >= 0 and lows[j] >= low:
                j = lower[j]
            if j < 0 or highs[j] >= total:
                break
            low, first, before = lows[j], spans[j][0], lower[j]
            del lows[j:], highs[j:], spans[j:], lower[j:]
            j = before
        lows.append(low)
        highs.append(total)
        spans.append((first, place))
        lower.append(j)
    return [(a, b, high - low) for (a, b), low, high in zip(spans, lows, highs)]


def segments_of(text: str, model: Model) -> tuple[int, list[tuple[int, int, float]]]:
    """(number of words, maximal segments by word position)."""
    found, lexicon, stems = words(text), model.lexicon, model.stems
    places = [i for i, w in enumerate(found) if w in lexicon or w[:STEM] in stems]
    scores = [lexicon[w] if w in lexicon else stems[w[:STEM]] for w in map(found.__getitem__, places)]
    return len(found), maximal_segments(scores, places, model.drift) if places else []


def evidence(n: int, segments: list[tuple[int, int, float]], model: Model) -> tuple[float, float, float, int]:
    """What a text shows: the calibrated score of its best segment, that of its best segments together, their share of words, and
    the number of segments that are significant by themselves.

    Scaled scores less the log of the search space are extreme-value distributed for the best segment; for the r best the
    sum gains log r!, and the r of the largest sum counts. So many weak passages weigh as much as a strong one.
    """
    if not segments:
        return -5.0, -5.0, 0.0, 0
    base = math.log(model.scale * max(n, 1))
    beyond = -math.log(-math.log1p(-model.level))
    scaled = sorted((model.rate * s - base for _, _, s in segments), reverse=True)
    good = sum(x > beyond for x in scaled)
    total, run = scaled[0], 0.0
    for r, x in enumerate(scaled, 1):
        if x <= -math.log(r):
            break
        run += x + math.log(r)
        total = max(total, run)
    covered = sum(b - a + 1 for a, b, s in segments if model.rate * s - base > beyond)
    return min(max(scaled[0], -5.0), 5.0), min(max(total, -5.0), 40.0), covered / max(n, 1), good


def features(found: list[str]) -> dict[str, int]:
    """Counts of a text's words, and of the stems of longer ones, which end in a tilde."""
    own: dict[str, int] = {}
    for w in found:
        own[w] = own.get(w, 0) + 1
        if len(w) > STEM:
            stem = w[:STEM] + "~"
            own[stem] = own.get(stem, 0) + 1
    return own


def _leaning(counted: DataFrame, n_toxic: int, n_clean: int, prior_words: float, least_docs: int, least_z: float, least_lean: float) -> DataFrame:
    """``(word, clean, lean)``: the smoothed log-odds of every word and stem that leans clearly by the variance of its estimate; clean leans only of words."""
    prior = prior_words * (F.col("toxic") + F.col("clean")) / (n_toxic + n_clean)
    odds = lambda y, n: F.log((F.col(y) + prior) / F.greatest(n + prior_words - F.col(y) - prior, F.lit(1.0)))
    leans = counted.where(F.col("docs") >= least_docs).withColumn("lean", odds("toxic", n_toxic) - odds("clean", n_clean))
    z = F.col("lean") / F.sqrt(1 / (F.col("toxic") + prior) + 1 / (F.col("clean") + prior))
    clear = ((z >= least_z) & (F.col("lean") >= least_lean)) | ((z <= -least_z) & (F.col("lean") <= -least_lean) & ~F.col("word").endswith("~"))
    return leans.where(clear).select("word", "clean", "lean")


def _rate(lexicon: dict[str, float], stems: dict[str, float], clean: dict[str, int], n_clean: int, drift: float) -> float:
    """The rate at which the moment generating function of a clean word's score is one. Each word counts under the one score it gets."""
    by_stem: dict[str, int] = {}
    for w in lexicon:
        if len(w) > STEM:
            by_stem[w[:STEM]] = by_stem.get(w[:STEM], 0) + clean[w]
    counts = [(clean[w], s) for w, s in lexicon.items()] + [(max(clean[f"{w}~"] - by_stem.get(w, 0), 0), s) for w, s in stems.items()]
    total = n_clean + 0.5 * len(counts)
    shares = [((n + 0.5) / total, s) for n, s in counts]
    shares.append((max(n_clean - sum(n for n, _ in counts), 0) / total, -drift))
    excess = lambda r: sum(p * math.exp(min(r * s, 60)) for p, s in shares) - 1
    low, high = 1e-4, 1.0
    while excess(high) < 0 and high < 50:
        high *= 2
    for _ in range(80):
        middle = (low + high) / 2
        low, high = (middle, high) if excess(middle) < 0 else (low, middle)
    return high


def extreme_scale(sizes: np.ndarray, best: np.ndarray, rate: float, least: float) -> float:
    """K of the extreme-value distribution by maximum likelihood: the best segment of n clean words tops s with probability 1 - exp(-K n exp(-rate s)).

    Texts without a segment count as those whose best score is below ``least``, the smallest a segment can have.
    """
    seen = best > 0
    mass = float((sizes * np.exp(-rate * np.where(seen, best, least))).sum())
    return max(int(seen.sum()), 1) / mass if mass > 0 else 1.0


def fit(
    docs: DataFrame, labels: DataFrame, label: str = "toxic", parts: int = 5, kept_out: int = 0, limit: int = MAX_TRAINING_DOCS, prior_share: float = 0.05, least_docs: int = 3, least_z: float = 2.5, least_lean: float = 2.0, drift: float = 1.0
) -> Model:
    """Fit on at most ``limit`` labelled documents outside the held-out fold: word counts on four fifths, calibration on the rest.

    Without labels, or with one class only, every text gets the share of toxic labels (one half if there are none).
    """
    spark = docs.sparkSession
    ship(spark)
    rows = materialize(training_rows(docs, labels, label, held_out("doc_id", parts, kept_out), limit).withColumn("fold", F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(5))), "training")

    def tally(batches):
        sums: dict[str, list[int]] = {}
        for batch in batches:
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                for w, n in features(words(text)).items():
                    row = sums.setdefault(w, [0, 0, 0])
                    row[1 if toxic else 2] += n
                    row[0] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), *[pa.array([v[i] for v in sums.values()], pa.int64()) for i in range(3)]], ["word", "docs", "toxic", "clean"])

    counted = rows.df.where("fold > 0").select("text", "label").mapInArrow(tally, "word string, docs long, toxic long, clean long").groupBy("word").agg(*[F.sum(c).alias(c) for c in ("docs", "toxic", "clean")])
    counted = materialize(counted, "words")
    sums = counted.df.where(~F.col("word").endswith("~")).agg(F.sum("toxic").alias("t"), F.sum("clean").alias("c")).first()
    share = rows.df.agg(F.avg("label").alias("p")).first()["p"]
    if not sums["t"] or not sums["c"]:
        p = min(max(0.5 if share is None else share, 1e-3), 1 - 1e-3)
        return Model({}, {}, drift, 1.0, 0.1, [math.log(p / (1 - p)), 0.0, 0.0, 0.0])
    leaning = _leaning(counted.df, sums["t"], sums["c"], prior_share * (sums["t"] + sums["c"]), least_docs, least_z, least_lean).collect()  # words of ``limit`` documents
    scores = {r["word"]: max(r["lean"] - drift, LEAST_SCORE) for r in leaning}
    clean = {r["word"]: r["clean"] for r in leaning}
    lexicon, stems = {w: v for w, v in scores.items() if w[-1] != "~"}, {w[:-1]: v for w, v in scores.items() if w[-1] == "~"}
    model = Model(lexicon, stems, drift, _rate(lexicon, stems, clean, sums["c"], drift), 1.0)
    calm = rows.df.where("fold = 0 and label = 0")
    bests = np.array([(r["n"], r["top"]) for r in calm.select(*_best_columns(calm, model)).collect()], dtype=np.float64).reshape(-1, 2)  # at most a fifth of the limit
    if len(bests):
        model.scale = extreme_scale(bests[:, 0], bests[:, 1], model.rate, min([v for v in scores.values() if v > 0], default=1.0))
    shown = rows.df.where("fold = 0")
    shown = shown.select("label", *_evidence_columns(shown, model)).collect()  # at most a fifth of the limit
    if len({r["label"] for r in shown}) == 2:
        x = np.array([[r["best"], r["together"], r["share"]] for r in shown])
        model.weights = [float(w) for w in fit_logistic(x, np.array([r["label"] for r in shown], dtype=np.float64))]
    rows.drop()
    counted.drop()
    return model


def _best_columns(df: DataFrame, model: Model):
    """The number of words of a text and the score of its best segment."""
    held = df.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("n long, top double")
    def run(text):
        import pandas as pd

        found = [segments_of(t or "", held.value) for t in text]
        return pd.DataFrame({"n": [n for n, _ in found], "top": [max((s for *_, s in x), default=0.0) for _, x in found]})

    shown = run("text")
    return [shown["n"].alias("n"), shown["top"].alias("top")]


def _evidence_columns(df: DataFrame, model: Model):
    held = df.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("best double, together double, share double")
    def run(text):
        import pandas as pd

        return pd.DataFrame([evidence(*segments_of(t or "", held.value), held.value)[:3] for t in text], columns=["best", "together", "share"])

    shown = run("text")
    return [shown["best"].alias("best"), shown["together"].alias("together"), shown["share"].alias("share")]


def score(docs: DataFrame, model: Model, parts: int = 5, kept_out: int = 0) -> DataFrame:
    """``doc_id, held_out, score, predicted, n_words, n_segments, passages`` of every document.

    ``passages`` are the significant segments by word positions, ends inclusive, with their scores. Null and empty texts
    have none and score as texts without evidence.
    """
    ship(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)
    passage = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64()), ("score", pa.float64())]))

    def run(batches):
        m = held.value
        base = -math.log(-math.log1p(-m.level))
        for batch in batches:
            out: list[tuple] = []
            for text in batch.column(1).to_pylist():
                n, found = segments_of(text or "", m)
                best, together, share, good = evidence(n, found, m)
                z = m.weights[0] + m.weights[1] * best + m.weights[2] * together + m.weights[3] * share
                p = 1 / (1 + math.exp(-min(max(z, -30), 30)))
                limit = base + math.log(m.scale * max(n, 1))
                out.append((p, int(p >= 0.5), n, good, [{"first": a, "last": b, "score": s} for a, b, s in found if m.rate * s > limit]))
            columns = list(zip(*out)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *[pa.array(c, t) for c, t in zip(columns, (pa.float64(), pa.int32(), pa.int64(), pa.int64(), passage))]],
                ["doc_id", "score", "predicted", "n_words", "n_segments", "passages"],
            )

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
        run, "doc_id long, score double, predicted int, n_words long, n_segments long, passages array<struct<first:long,last:long,score:double>>"
    )
    return scored.select("doc_id", held_out("doc_id", parts, kept_out).alias("held_out"), "score", "predicted", "n_words", "n_segments", "passages")


def without_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that are not predicted toxic, all columns as they were; rows with a null id are kept."""
    flagged = score(docs, fit(docs, labels)).where("predicted = 1").select("doc_id").distinct()
    return docs.join(flagged, "doc_id", "left_anti").select(*docs.columns)
