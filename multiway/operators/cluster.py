"""Matching and clustering: assignment, K-means on factor rows, a plane embedding, accuracy."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import setting
from .tall import Tall


def assignment(cost: np.ndarray) -> np.ndarray:
    """Column for each row that minimises the total cost (rows <= columns), by shortest augmenting paths."""
    n, m = cost.shape
    if n > m:
        raise ValueError("more rows than columns")
    row_price, col_price = np.zeros(n + 1), np.zeros(m + 1)
    owner, back = np.zeros(m + 1, int), np.zeros(m + 1, int)
    for i in range(1, n + 1):
        owner[0], j = i, 0
        least, used = np.full(m + 1, np.inf), np.zeros(m + 1, bool)
        while owner[j]:
            used[j] = True
            free = ~used[1:]
            reduced = cost[owner[j] - 1] - row_price[owner[j]] - col_price[1:]
            better = free & (reduced < least[1:])
            least[1:][better] = reduced[better]
            back[1:][better] = j
            following = 1 + int(np.where(free, least[1:], np.inf).argmin())
            step = least[following]
            row_price[owner[used]] += step
            col_price[used] -= step
            least[1:][free] -= step
            j = following
        while j:
            owner[j] = owner[back[j]]
            j = back[j]
    out = np.zeros(n, int)
    for j in range(1, m + 1):
        if owner[j]:
            out[owner[j] - 1] = j - 1
    return out


def cluster_accuracy(pairs: DataFrame, label: str = "label", cluster: str = "cluster") -> float:
    """Share of samples in the best one-to-one match of clusters and labels; only the contingency table is gathered."""
    rows = pairs.groupBy(label, cluster).agg(F.count("*").alias("n")).collect()
    labels, clusters = sorted({r[label] for r in rows}), sorted({r[cluster] for r in rows})
    size = max(len(labels), len(clusters))
    table = np.zeros((size, size))
    for r in rows:
        table[labels.index(r[label]), clusters.index(r[cluster])] = r["n"]
    match = assignment(-table)
    return float(table[np.arange(size), match].sum() / max(1, table.sum()))


def _parts(x: np.ndarray | Tall) -> Iterator[tuple[int, np.ndarray]]:
    return x.blocks() if isinstance(x, Tall) else iter([(0, x)])


def lloyd(x: np.ndarray | Tall, k: int, seed: int = 1, starts: int = 8, steps: int = 60) -> np.ndarray:
    """K-means of a matrix on the driver: spread starts, the best of several. Distances come from matrix products, so nothing of
    rows x clusters x columns is made. Of a tall matrix only a label and a distance for each row are in memory."""
    best, labels = np.inf, None

    def row(at: int) -> np.ndarray:
        return x.read(at, at + 1) if isinstance(x, Tall) else x[[at]]

    def distances(part: np.ndarray, centres: np.ndarray) -> np.ndarray:
        return np.maximum(0, (part * part).sum(1)[:, None] - 2 * part @ centres.T + (centres * centres).sum(1))

    for s in range(starts):
        random = np.random.default_rng(seed + s)
        centres = row(random.integers(len(x)))
        while len(centres) < k:
            far = np.concatenate([distances(part, centres).min(1) for _, part in _parts(x)])
            np.cumsum(far, out=far)
            at = min(int(far.searchsorted(random.random() * far[-1], side="right")), len(x) - 1) if far[-1] else random.integers(len(x))
            centres = np.vstack([centres, row(at)])
        own = np.empty(len(x), np.int32)
        for _ in range(steps):
            held, sums = np.zeros((k, 1)), np.zeros_like(centres)
            for lo, part in _parts(x):
                near = distances(part, centres).argmin(1)
                own[lo : lo + len(part)] = near
                held += np.bincount(near, minlength=k)[:, None]
                sums += (near == np.arange(k)[:, None]).astype(float) @ part
            moved = np.where(held > 0, sums / np.maximum(held, 1), centres)
            if np.allclose(moved, centres):
                break
            centres = moved
        cost = sum(((part - centres[own[lo : lo + len(part)]]) ** 2).sum() for lo, part in _parts(x))
        if cost < best:
            best, labels = cost, own
    return labels


def _labelled(spark: SparkSession, labels: np.ndarray, step: int) -> DataFrame:
    """(i, cluster); beyond `step` rows in several pieces, each of which leaves the driver before the next. They go as
    Arrow batches: as a local relation each row is an object of the JVM, and sent so."""
    from ..sources.storage import stored

    def piece(lo: int) -> DataFrame:
        own = labels[lo : lo + step].astype(np.int32)
        with setting(spark, "spark.sql.execution.arrow.localRelationThreshold", "0"):
            return spark.createDataFrame(pa.table({"i": np.arange(lo, lo + len(own)), "cluster": own}))

    return reduce(DataFrame.unionByName, [piece(0), *[stored(piece(lo)) for lo in range(step, len(labels), step)]])


def kmeans(spark: SparkSession, features: np.ndarray | Tall, k: int, seed: int = 1, driver_rows: int = 1_000_000) -> DataFrame:
    """(i, cluster) of rows; matrices beyond driver_rows are clustered on the executors. Up to there, and where it lies in a file, the
    matrix stays where it is: to send it as row objects takes longer than the clustering."""
    if len(features) <= driver_rows or isinstance(features, Tall):
        return _labelled(spark, lloyd(features, k, seed), driver_rows)
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.linalg import Vectors

    rows = spark.createDataFrame([(i, Vectors.dense([float(x) for x in r])) for i, r in enumerate(features)], ["i", "features"])
    model = KMeans(k=k, seed=seed, maxIter=50, initSteps=5).fit(rows)
    return model.transform(rows).select(F.col("i").cast("long"), F.col("prediction").alias("cluster"))


def plane(x: np.ndarray | Tall, perplexity: float = 30.0, steps: int = 300, limit: int = 3000) -> np.ndarray:
    """Exact t-SNE to two components, started from the leading principal ones; those alone beyond `limit` rows."""
    if isinstance(x, Tall) and len(x) > limit:
        middle = sum(part.sum(0) for _, part in x.blocks()) / len(x)
        v = np.linalg.eigh(sum((part - middle).T @ (part - middle) for _, part in x.blocks()))[1][:, ::-1][:, :2]
        return x.mapped(lambda part: np.pad((part - middle) @ v, ((0, 0), (0, 2 - v.shape[1]))))
    x = x.whole() if isinstance(x, Tall) else x
    x = x - x.mean(0)
    _, s, vt = np.linalg.svd(x, full_matrices=False)
    y = x @ vt[:2].T
    y = np.pad(y, ((0, 0), (0, 2 - y.shape[1])))
    if len(x) > limit or len(x) < 10:
        return y
    d = np.maximum(0, (x**2).sum(1)[:, None] + (x**2).sum(1)[None] - 2 * x @ x.T)
    np.fill_diagonal(d, np.inf)
    low, high = np.zeros(len(x)), np.full(len(x), np.inf)
    beta, target = np.ones(len(x)) / np.median(d[np.isfinite(d)]), np.log(min(perplexity, (len(x) - 1) / 3))
    for _ in range(50):
        p = np.exp(-d * beta[:, None])
        total = np.maximum(p.sum(1), 1e-300)
        entropy = np.log(total) + beta * (np.where(np.isfinite(d), d, 0) * p).sum(1) / total
        more = entropy > target
        low, high = np.where(more, beta, low), np.where(more, high, beta)
        beta = np.where(np.isfinite(high), (low + high) / 2, beta * 2)
    p = p / total[:, None]
    p = np.maximum((p + p.T) / (2 * len(x)), 1e-12)
    y, move, gain = y / max(y[:, 0].std(), 1e-12) * 1e-4, np.zeros_like(y), np.ones_like(y)
    for k in range(steps):
        q = 1 / (1 + np.maximum(0, (y**2).sum(1)[:, None] + (y**2).sum(1)[None] - 2 * y @ y.T))
        np.fill_diagonal(q, 0)
        w = (p * (12 if k < 100 else 1) - q / q.sum()) * q
        g = 4 * (w.sum(1)[:, None] * y - w @ y)
        gain = np.maximum(np.where(np.sign(g) != np.sign(move), gain + 0.2, gain * 0.8), 0.01)
        move = (0.5 if k < 100 else 0.8) * move - 200 * gain * g
        y = y + move
    return y - y.mean(0)
