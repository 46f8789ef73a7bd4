"""Quality by a sparse rule ensemble: tree paths over text statistics as rules, lasso logistic weights, Spark columns.

Statistics and scoring are Spark expressions; only a bounded sample of labelled statistics reaches the driver, where the
trees and weights are fitted.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from tidegraph.llm.labels import held_out, training_rows

#: Bound of the fit: labelled documents used. Trees grown and their depth; every path of them is a rule that the lasso sees.
MAX_TRAINING_DOCS = 8_000
TREES, DEPTH = 24, 3


def statistics(text: str = "text") -> dict[str, Column]:
    """Statistics of a text by name; all are 0 for null or empty texts."""
    t = F.coalesce(F.col(text), F.lit(""))
    size = F.length(t)
    share = lambda c: F.when(size > 0, c / size).otherwise(0.0).cast("double")
    tokens = F.split(t, " ")
    lines = F.split(t, "\n")
    without = lambda pattern: size - F.length(F.regexp_replace(t, pattern, ""))
    ratio = lambda a, b: F.when(size > 0, a / b).otherwise(0.0).cast("double")
    stops = F.length(F.regexp_replace(t, "[^.!?]+", ""))
    return {
        "chars": F.log1p(size.cast("double")),
        "token_length": ratio(size, F.size(tokens)),
        "distinct_tokens": ratio(F.size(F.array_distinct(tokens)), F.size(tokens)),
        "distinct_lines": ratio(F.size(F.array_distinct(lines)), F.size(lines)),
        "line_length": F.when(size > 0, F.log1p(size / F.size(lines))).otherwise(0.0).cast("double"),
        "sentence_length": ratio(F.size(tokens), stops + 1),
        "stops": share(stops),
        "commas": share(size - F.length(F.replace(t, F.lit(","), F.lit("")))),
        "capitals": share(without("[A-Z]+")),
        "digits": share(without("[0-9]+")),
        "symbols": share(without(r"[#-&*+/<=>@\[-`{-~]+")),
        "marks_in_a_row": share(without(r"([!-/:-@\[-`{-~])\1+")),
        "long_tokens": share(without("[A-Za-z]{20,}")),
    }


@dataclass
class Rule:
    """A conjunction of (statistic, is above, threshold)."""

    parts: tuple[tuple[str, bool, float], ...]
    weight: float = 0.0

    def column(self) -> Column:
        out = F.lit(True)
        for name, above, limit in self.parts:
            out = out & ((F.col(name) > limit) if above else (F.col(name) <= limit))
        return out

    def holds(self, x: np.ndarray, names: list[str]) -> np.ndarray:
        out = np.ones(len(x), dtype=bool)
        for name, above, limit in self.parts:
            v = x[:, names.index(name)]
            out &= (v > limit) if above else (v <= limit)
        return out


@dataclass
class Model:
    intercept: float
    rules: list[Rule]


def _grow(x: np.ndarray, target: np.ndarray, names: list[str], depth: int, least: int, rng: np.random.Generator, path: tuple = ()) -> list[tuple[tuple, float, np.ndarray]]:
    """Paths of a regression tree: (parts, mean, rows) of every node below the root."""
    if depth == 0 or len(x) < 2 * least:
        return []
    best = None
    for f in rng.permutation(len(names))[: max(4, len(names) // 2)]:
        v = x[:, f]
        for limit in np.unique(np.quantile(v, np.linspace(0.05, 0.95, 19))):
            left = v <= limit
            n = left.sum()
            if n < least or len(v) - n < least:
                continue
            gain = target[left].sum() ** 2 / n + target[~left].sum() ** 2 / (len(v) - n)
            if best is None or gain > best[0] + 1e-12:
                best = (gain, f, float(limit), left)
    if best is None or best[0] - target.sum() ** 2 / len(x) < 1e-6:
        return []
    _, f, limit, left = best
    out = []
    for above, rows in ((False, left), (True, ~left)):
        own = (*path, (names[f], above, limit))
        out.append((own, float(target[rows].mean())))
        out += _grow(x[rows], target[rows], names, depth - 1, least, rng, own)
    return out


def rules_of(x: np.ndarray, y: np.ndarray, names: list[str], seed: int = 7) -> list[Rule]:
    """Rules from boosted trees on random halves of the rows, without doubles."""
    rng = np.random.default_rng(seed)
    p = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
    margin = np.full(len(y), np.log(p / (1 - p)))
    found: dict[tuple, Rule] = {}
    for _ in range(TREES):
        residual = y - 1 / (1 + np.exp(-margin))
        rows = rng.random(len(y)) < 0.5
        if rows.sum() < 20:
            rows[:] = True
        paths = _grow(x[rows], residual[rows], names, DEPTH, max(5, int(rows.sum()) // 200), rng)
        parents = {parts[:-1] for parts, *_ in paths}
        for parts, mean in paths:
            rule = Rule(tuple(sorted(parts)))
            found.setdefault(rule.parts, rule)
            if parts not in parents:
                margin += 2.0 * mean * Rule(parts).holds(x, names)
    return list(found.values())


def lasso(z: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 400) -> tuple[float, np.ndarray]:
    """L1 logistic regression by accelerated proximal gradients on centred columns; the intercept isn't penalised."""
    mean = z.mean(0)
    c = z - mean
    size = np.linalg.norm(c, 2) ** 2 / len(y) / 4 + 0.25
    w, b, v, u, t = np.zeros(z.shape[1]), 0.0, np.zeros(z.shape[1]), 0.0, 1.0
    for _ in range(rounds):
        g = 1 / (1 + np.exp(-np.clip(c @ v + u, -30, 30))) - y
        nw, nb = v - c.T @ g / len(y) / size, u - g.mean() / size
        nw = np.sign(nw) * np.maximum(np.abs(nw) - penalty / size, 0)
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, u = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    return b - float(mean @ w), w


def fit_rules(x: np.ndarray, y: np.ndarray, names: list[str], penalty: float = 0.0015) -> Model:
    if len(y) == 0 or y.min() == y.max():
        p = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
        return Model(float(np.log(p / (1 - p))), [])
    rules = rules_of(x, y, names)
    z = np.column_stack([r.holds(x, names) for r in rules]).astype(np.float64) if rules else np.zeros((len(y), 0))
    keep = np.flatnonzero(z.std(0) > 1e-9)
    if not len(keep):
        p = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
        return Model(float(np.log(p / (1 - p))), [])
    b, w = lasso(z[:, keep], y, penalty)
    return Model(b, [Rule(rules[k].parts, float(v)) for k, v in zip(keep, w) if abs(v) > 1e-6])


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", parts: int = 4, kept_out: int = 2, limit: int = MAX_TRAINING_DOCS) -> Model:
    """Fit on at most ``limit`` labelled documents outside the held-out fold. Without labels or with one class every text gets its share."""
    stats = statistics()
    rows = training_rows(docs, labels, label, held_out("doc_id", parts, kept_out), limit)
    sample = sorted(tuple(r) for r in rows.select("label", *[c.alias(n) for n, c in stats.items()], "doc_id").collect())  # bounded by limit
    x = np.array([r[1:-1] for r in sample], dtype=np.float64).reshape(len(sample), len(stats))
    return fit_rules(x, np.array([r[0] for r in sample], dtype=np.float64), list(stats))


def score(docs: DataFrame, model: Model, parts: int = 4, kept_out: int = 2, threshold: float = 0.7) -> DataFrame:
    """``doc_id, held_out, score, predicted, n_rules`` of every document, as Spark expressions alone.

    Null and empty texts have statistics of 0 and score by the rules that hold then.
    """
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *[c.alias(n) for n, c in statistics().items()])
    z, fired = F.lit(model.intercept), F.lit(0)
    for rule in model.rules:
        z = z + F.when(rule.column(), F.lit(rule.weight)).otherwise(F.lit(0.0))
        fired = fired + F.when(rule.column(), 1).otherwise(0)
    scored = ids.select("doc_id", (1 / (1 + F.exp(-z))).alias("score"), fired.alias("n_rules"))
    return scored.select("doc_id", held_out("doc_id", parts, kept_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_rules")
