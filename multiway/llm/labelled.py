"""Labelled rows for training: bounded by a parameter, never from the held-out fold, text only."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Labelled rows that a classifier is fitted on, at most; taken in order of a hash of the id.
TRAIN_ROWS = 6000
#: Tasks that read the training texts.
PARTS = 24


def held_out(id_col: str = "doc_id"):
    """The fold that no label may be learnt from."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, limit: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, text, label of at most `limit` documents, one row an id (of repeated ids the least text, the greater label).

    The bound is put on ids, by a hash of them, before any text moves; texts are then dealt over PARTS tasks.
    """
    chosen = labels.filter(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max(label).cast("int").alias("label"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit)
    rows = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")
    return rows.groupBy("doc_id").agg(F.min("text").alias("text"), F.first("label").alias("label")).repartition(PARTS)


def logistic(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_logistic(x: np.ndarray, y: np.ndarray, prior: np.ndarray, strength: float = 1.0, steps: int = 60) -> np.ndarray:
    """Weights (the last is the bias) that maximise likelihood times a Gaussian around `prior`, by Newton's method."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = prior.astype(float).copy()
    for _ in range(steps):
        p = logistic(x @ w)
        gradient = x.T @ (y - p) - strength * (w - prior)
        hessian = (x * (p * (1 - p))[:, None]).T @ x + strength * np.eye(len(w))
        step = np.linalg.solve(hessian, gradient)
        w += step * min(1.0, 4 / (np.abs(step).max() + 1e-12))
        if np.abs(step).max() < 1e-8:
            break
    return w
