"""Quality classifier: naive Bayes support vectors over n-gram indicators.

Three kinds of n-grams are indicators: hashed word unigrams and bigrams (small letters of a word as it stands between white
space); n-grams of one to four character classes (small letter, capital, digit, blank, line end, and kinds of punctuation; runs are
cut at two), which see shape and junk but no wording; and n-grams over a stream that says of each word whether it repeats the one
before or one of the REPEATS before that. Indicators are scaled by the log-ratio of class counts, and a linear model with squared
hinge loss is fitted to them by dual coordinate descent; its margins are made probabilities by a logistic fit.

Defined results: null and empty texts have no n-grams and get the score of the intercept; texts are read whole whatever their
length; rows keep their multiplicity; with no labelled row of one class every score is the share of label 1 (0.5 if there
are none); labels, lang, source and doc_id never enter a score; the fit doesn't depend on the order of rows; other columns may
have any name.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import MULTIPLIERS, WordHashes, boxed, mixed, sliced_texts, table, unboxed
from .labelled import TRAIN_ROWS, fit_logistic, held_out, logistic, training_rows

ORDER = 4
#: How far back a word is looked for, and buckets of hashed word n-grams (a power of two).
REPEATS, BUCKETS = 8, 1 << 16


def _classes() -> np.ndarray:
    kinds = np.full(256, 13, np.uint16)
    for k, chars in enumerate(("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", " \t", "\n\r", ".,", "!", "|", "%$&*#", "?;:", "\"'()[]{}", "<>", "-_/\\")):
        kinds[np.frombuffer(chars.encode(), np.uint8)] = k
    kinds[128:] = 0
    return kinds


KINDS, ALPHABET = _classes(), 14
#: Codes of character n-grams of each order, then of word-repeat n-grams of orders 1 to 4 over three symbols, then word n-grams.
STARTS = np.cumsum([0, *(ALPHABET**n for n in range(1, ORDER + 1)), *(3**n for n in range(1, ORDER + 1))])
N_FEATURES = int(STARTS[-1]) + BUCKETS


def _grams(symbols: np.ndarray, base: int, first: int, seen: np.ndarray) -> None:
    code = symbols.astype(np.int64)
    for n in range(1, ORDER + 1):
        seen[STARTS[first + n - 1] + code] = True
        if len(code) < 2 or n == ORDER:
            break
        code = code[:-1] * base + symbols[n:]


def active(text: str | None, hashes: WordHashes | None = None) -> np.ndarray:
    """Sorted codes of the n-grams that a text has."""
    raw = (text or "").encode()
    if not raw:
        return np.empty(0, np.int64)
    seen = np.zeros(N_FEATURES, bool)
    kinds = KINDS[np.frombuffer(raw, np.uint8)]
    if len(kinds) > 2:
        kinds = kinds[np.concatenate([[True, True], (kinds[2:] != kinds[1:-1]) | (kinds[2:] != kinds[:-2])])]
    _grams(kinds, ALPHABET, 0, seen)
    words = raw.lower().split()
    if words:
        known = (hashes if hashes is not None else WordHashes()).of(words)
        repeat = np.zeros(len(words), np.int64)
        for back in range(min(REPEATS, len(words) - 1), 0, -1):
            repeat[back:][known[back:] == known[:-back]] = 2 if back == 1 else 1
        _grams(repeat, 3, ORDER, seen)
        pairs = mixed(known[:-1] * MULTIPLIERS[0] + known[1:])
        for grams in (known, pairs):
            seen[int(STARTS[-1]) + (mixed(grams) >> np.uint64(48)).astype(np.int64) % BUCKETS] = True
    return np.flatnonzero(seen)


@dataclass
class NbSvm:
    """weights: of the descent; ratio: log-count ratios that scale indicators; slope and offset: of the logistic fit."""

    weights: np.ndarray
    bias: float
    slope: float
    offset: float
    ratio: np.ndarray | None = None

    @classmethod
    def of(cls, w: np.ndarray, b: float, ratio: np.ndarray) -> NbSvm:
        return cls(w * ratio, b, 1.0, 0.0, ratio)

    def margin(self, codes: np.ndarray) -> float:
        if self.ratio is None or not len(codes):
            return self.bias
        return float(self.weights[codes].sum() / max(1e-9, np.sqrt((self.ratio[codes] ** 2).sum())) + self.bias)

    def score(self, text: str | None, hashes: WordHashes | None = None) -> float:
        return float(logistic(self.slope * self.margin(active(text, hashes)) + self.offset))


def dual_descent(rows: list[np.ndarray], ratio: np.ndarray, y: np.ndarray, cost: np.ndarray, sweeps: int = 30) -> tuple[np.ndarray, float]:
    """Linear squared-hinge model over rows of active codes with value ratio[code], by dual coordinate descent.

    Each row is scaled to unit length, so long texts weigh no more than short ones.
    """
    w, b, alpha, order = np.zeros(len(ratio)), 0.0, np.zeros(len(rows)), np.random.default_rng(7)
    values = [ratio[r] / max(1e-9, float(np.sqrt((ratio[r] ** 2).sum()))) for r in rows]
    diagonal = np.array([v @ v + 1.0 for v in values]) + 1 / (2 * cost)
    for _ in range(sweeps):
        moved = 0.0
        for i in order.permutation(len(rows)):
            slope = y[i] * (w[rows[i]] @ values[i] + b) - 1 + alpha[i] / (2 * cost[i])
            step = max(alpha[i] - slope / diagonal[i], 0.0) - alpha[i]
            if step:
                alpha[i] += step
                w[rows[i]] += step * y[i] * values[i]
                b += step * y[i]
                moved = max(moved, abs(step))
        if moved < 1e-4:
            break
    return w, b


def fit_codes(rows: list[np.ndarray], labels: list[int], min_rows: int = 3) -> NbSvm:
    y = np.where(np.asarray(labels) == 1, 1.0, -1.0)
    if not len(y) or len(set(y)) < 2:
        share = (np.asarray(labels) == 1).mean() if len(y) else 0.5
        share = min(max(share, 1e-6), 1 - 1e-6)
        return NbSvm(np.zeros(N_FEATURES), 0.0, 1.0, float(np.log(share / (1 - share))))
    counts = {s: np.bincount(np.concatenate([r for r, v in zip(rows, y, strict=True) if v == s]), minlength=N_FEATURES) for s in (1.0, -1.0)}
    kept = counts[1.0] + counts[-1.0] >= min_rows
    share = {s: (counts[s] + 1) / ((y == s).sum() + 2) for s in counts}
    ratio = np.where(kept, np.log(share[1.0] / share[-1.0]), 0.0)
    rows = [r[ratio[r] != 0] for r in rows]
    cost = np.where(y > 0, len(y) / (2 * (y > 0).sum()), len(y) / (2 * (y < 0).sum()))
    # Margins for the logistic fit come from folds that did not train on them.
    fold, margin = np.arange(len(y)) % 3, np.zeros(len(y))
    for f in range(3):
        own = np.flatnonzero(fold != f)
        if len(set(y[own])) == 2:
            part = NbSvm.of(*dual_descent([rows[i] for i in own], ratio, y[own], cost[own]), ratio)
            margin[fold == f] = [part.margin(rows[i]) for i in np.flatnonzero(fold == f)]
    model = NbSvm.of(*dual_descent(rows, ratio, y, cost), ratio)
    slope, offset = fit_logistic(margin[:, None], (y > 0).astype(float), np.array([2.0, 0.0]), 0.1)
    model.slope, model.offset = max(float(slope), 0.05), float(offset)
    return model


def fit_quality(docs: DataFrame, labels: DataFrame, limit: int = TRAIN_ROWS) -> NbSvm:
    """Fitted on at most `limit` labelled rows outside the held-out fold."""
    packed = training_rows(docs, labels, "quality", limit).mapInArrow(_packed, "doc_id long, codes binary, label int").collect()
    packed.sort(key=lambda r: r["doc_id"])
    return fit_codes([np.frombuffer(r["codes"], np.uint32).astype(np.int64) for r in packed], [r["label"] for r in packed])


def _packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hashes = WordHashes()
    for batch in sliced_texts(batches, "text"):
        codes = [active(t, hashes).astype(np.uint32).tobytes() for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array(codes, pa.binary()), batch.column("label")], ["doc_id", "codes", "label"])


def score_quality(docs: DataFrame, model: NbSvm, keep: list[str], text_col: str = "text", out: str = "score") -> DataFrame:
    """The kept columns and `out`: one scan, no shuffle."""
    return unboxed(_scored(docs, model, keep, text_col), F.col("score").alias(out))


def of_quality(docs: DataFrame, model: NbSvm, least: float = 0.5) -> DataFrame:
    """All columns of the documents that score `least` or more."""
    return unboxed(_scored(docs, model, docs.columns).filter(F.col("score") >= least))


def _scored(docs: DataFrame, model: NbSvm, keep: list[str], text_col: str = "text") -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, hashes = shared.value, WordHashes()
        for batch in sliced_texts(batches, "text"):
            scores = pa.array([m.score(t, hashes) for t in batch.column("text").to_pylist()], pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column("row"), scores], ["row", "score"])

    chosen = boxed(docs, keep, text_col)
    return chosen.mapInArrow(run, chosen.select("row").schema.add("score", "double"))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit_quality(docs, table(spark, sf_dir, "labels"))
    scored = score_quality(docs, model, ["doc_id"])
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
