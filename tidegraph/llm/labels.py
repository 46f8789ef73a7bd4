"""Labelled rows for fitting, and a small logistic regression."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F


def held_out(id_col: str, parts: int, kept_out: int) -> Column:
    """True for rows whose crc32 of the id's text leaves ``kept_out`` modulo ``parts``; false for a null id."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % parts == kept_out, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, is_held_out: Column, limit: int) -> DataFrame:
    """``(doc_id, text, label)`` of at most ``limit`` labelled documents outside the held-out fold, those with the least hash of their id.

    Rows without a label are left out; of several labels of a document the largest counts. ``limit`` bounds what is broadcast.
    """
    chosen = (
        labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~is_held_out)
        .groupBy("doc_id")
        .agg(F.max(label).cast("int").alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(limit)
    )
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "label")


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 60) -> np.ndarray:
    """Ridge logistic regression by damped Newton steps; the first weight is the intercept, which isn't shrunk."""
    x = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(x.shape[1])
    shrink = np.full(x.shape[1], ridge)
    shrink[0] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + np.diag(shrink), x.T @ (y - p) - shrink * w)
        w += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-7:
            break
    return w
