"""Orthonormal bases of tall matrices: on the driver, and for factor rows that never leave the executors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tall import Tall


def basis_map(gram: np.ndarray, rtol: float = 1e-12) -> np.ndarray:
    """W with (Z W)t(Z W) = I from ZtZ; directions under rtol of the largest are dropped, so the rank may shrink."""
    w, q = np.linalg.eigh(gram)
    keep = w > rtol * max(w.max(initial=0), 1e-300)
    order = np.argsort(-w[keep])
    q = q[:, keep]
    # Signs are fixed, so rounding (another grid, another order of sums) doesn't turn the basis.
    q = q * np.where(q[np.abs(q).argmax(0), np.arange(q.shape[1])] < 0, -1.0, 1.0)
    return (q / np.sqrt(w[keep]))[:, order]


def polish_map(gram: np.ndarray) -> np.ndarray:
    """The symmetric inverse root: near the identity it stays near it, where eigenvectors would be arbitrary."""
    w, q = np.linalg.eigh(gram)
    return (q / np.sqrt(w)) @ q.T


def orth(z: np.ndarray, how: str = "gram", rtol: float = 1e-12, passes: int = 2) -> np.ndarray:
    """gram: eigenvectors of the small Gram, twice because it squares the condition number; qr: Householder."""
    if how == "qr" and isinstance(z, Tall):
        raise ValueError("a tall matrix gets its basis by the Gram")
    if how == "qr":
        u, s, _ = np.linalg.svd(z, full_matrices=False)
        return u[:, s > np.sqrt(rtol) * max(s.max(initial=0), 1e-300)]
    if how != "gram":
        raise ValueError(f"unknown way {how!r}")
    for k in range(passes):
        z = z @ (polish_map(z.T @ z) if k else basis_map(z.T @ z, rtol))
    return z


def _partial(rows: DataFrame, column: str, kernel) -> list[np.ndarray]:
    """One small matrix from each partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if batch.num_rows:
                m = batch.column(0).flatten().to_numpy().reshape(batch.num_rows, -1)
                total = kernel(total, m)
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.shape[1]], pa.int32()), pa.array([total.tobytes()], pa.binary())], ["k", "m"])

    return [np.frombuffer(r["m"]).reshape(-1, r["k"]) for r in rows.select(column).mapInArrow(run, "k int, m binary").collect()]


def gram_rows(rows: DataFrame, column: str = "f") -> np.ndarray:
    """ZtZ of rows: a small matrix for each partition, summed."""
    return sum(_partial(rows, column, lambda t, m: m.T @ m if t is None else t + m.T @ m))


def times_rows(rows: DataFrame, w: np.ndarray, column: str = "f") -> DataFrame:
    """Rows times a small matrix: a projection in Arrow batches, nothing moves."""
    schema = rows.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index(column)
            m = np.stack([np.asarray(x) for x in batch.column(at).to_pylist()]) @ w if batch.num_rows else np.empty((0, w.shape[1]))
            yield batch.set_column(at, column, pa.array(list(m), pa.list_(pa.float64())))

    return rows.mapInArrow(run, schema)


def orth_rows(rows: DataFrame, how: str = "gram", rtol: float = 1e-12, passes: int = 2, column: str = "f") -> DataFrame:
    """Orthonormal columns for rows (i, f). gram: Gram and eigenvectors; tsqr: a QR for each partition, then one of their R."""
    if how == "tsqr":
        parts = _partial(rows, column, lambda t, m: np.linalg.qr(m if t is None else np.vstack([t, m]), mode="r"))
        _, s, vt = np.linalg.svd(np.linalg.qr(np.vstack(parts), mode="r"))
        keep = s > np.sqrt(rtol) * max(s.max(initial=0), 1e-300)
        return times_rows(rows, vt[keep].T / s[keep], column)
    for k in range(passes):
        small = gram_rows(rows, column)
        rows = times_rows(rows, polish_map(small) if k else basis_map(small, rtol), column)
    return rows


def orth_error(u: np.ndarray) -> float:
    return float(np.abs(u.T @ u - np.eye(u.shape[1])).max())


def subspace_distance(a: np.ndarray, b: np.ndarray) -> float:
    """Frobenius distance of the projectors of two orthonormal bases, from their small cross-Gram."""
    return float(np.sqrt(max(0.0, a.shape[1] + b.shape[1] - 2 * ((a.T @ b) ** 2).sum())))


def random_rows(spark, rows: int, cols: int, seed: int) -> DataFrame:
    """A stored-free Gaussian matrix as rows (i, f)."""
    from ..functions.counter import gauss_col

    return spark.range(rows).select(F.col("id").alias("i"), F.array(*[gauss_col(seed, [F.col("id"), F.lit(r)]) for r in range(cols)]).alias("f"))
