"""Kernels over cells (i1..iN, v) and factor rows (i, f), as DataFrame plans; small matrices stay in numpy.

Everything here is joins, projections and partially aggregated sums, so Catalyst plans it; a factor is broadcast by
Spark only when its size allows. Absent cells are zeros.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from math import prod

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.counter import gauss_col, sign_col

#: Elements beyond which explicit products and reconstructions are refused.
EXPLICIT_LIMIT = 10_000_000


def modes_of(cells: DataFrame) -> list[str]:
    return [c for c in cells.columns if c != "v"]


# Small dense matrices -------------------------------------------------------------------------------------------


def khatri_rao(mats: Sequence[np.ndarray], skip: int | None = None) -> np.ndarray:
    """Column-wise Kronecker product, the highest mode slowest."""
    chosen = [m for k, m in enumerate(mats) if k != skip]
    rank = chosen[0].shape[1]
    if prod(m.shape[0] for m in chosen) * rank > EXPLICIT_LIMIT:
        raise ValueError("this product is too large to build; use mttkrp, which never builds it")
    return reduce(lambda acc, m: np.einsum("ir,jr->ijr", m, acc).reshape(-1, rank), chosen[1:], chosen[0])


def kronecker(mats: Sequence[np.ndarray], skip: int | None = None) -> np.ndarray:
    chosen = [m for k, m in enumerate(mats) if k != skip]
    if prod(m.size for m in chosen) > EXPLICIT_LIMIT:
        raise ValueError("this product is too large to build")
    return reduce(lambda acc, m: np.kron(m, acc), chosen)


def hadamard(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return a * b


def hdiv(a: np.ndarray, b: np.ndarray, eps: float = 1e-12) -> np.ndarray:
    """Element-wise quotient that never divides by zero."""
    return a / (b + eps)


def gram_hadamard(grams: Sequence[np.ndarray], skip: int | None = None) -> np.ndarray:
    """BtB of the product of all factors but one, from their Grams."""
    return reduce(np.multiply, [g for k, g in enumerate(grams) if k != skip])


def unfold_dense(x: np.ndarray, n: int) -> np.ndarray:
    return np.moveaxis(x, n, 0).reshape(x.shape[n], -1, order="F")


def fold_dense(m: np.ndarray, shape: Sequence[int], n: int) -> np.ndarray:
    rest = [s for k, s in enumerate(shape) if k != n]
    return np.moveaxis(m.reshape([shape[n], *rest], order="F"), 0, n)


def multiply(x: np.ndarray, m: np.ndarray, n: int) -> np.ndarray:
    """x times m (rows: new size) in mode n."""
    return np.moveaxis(np.tensordot(m, x, (1, n)), 0, n)


def multiply_all(x: np.ndarray, mats: Sequence[np.ndarray], skip: int | None = None, transpose: bool = False) -> np.ndarray:
    """All modes but one, the one that shrinks most first."""
    todo = [(m.T if transpose else m, k) for k, m in enumerate(mats) if k != skip]
    for m, k in sorted(todo, key=lambda t: t[0].shape[0] / t[0].shape[1]):
        x = multiply(x, m, k)
    return x


def cp_dense(factors: Sequence[np.ndarray], weights: np.ndarray | None = None) -> np.ndarray:
    """All cells of a CP model, for small shapes."""
    shape = [f.shape[0] for f in factors]
    if prod(shape) > EXPLICIT_LIMIT * 10:
        raise ValueError("too many cells; reconstruct at chosen cells instead")
    head = factors[0] if weights is None else factors[0] * weights
    return (head @ khatri_rao(factors[1:]).T).reshape(shape, order="F")


def core_mttkrp(core: np.ndarray, vs: Sequence[np.ndarray], n: int, how: str = "contract") -> np.ndarray:
    """G_(n) times the Khatri-Rao product of the other small matrices.

    explicit: builds the product; contract: a component at a time by contractions; columnwise: nonzeros of the core
    only; reuse is what `shared_mttkrp` does for all modes at once.
    """
    if how == "explicit":
        return unfold_dense(core, n) @ khatri_rao(vs, skip=n)
    if how == "columnwise":
        at = np.nonzero(core)
        values = np.repeat(core[at][:, None], vs[0].shape[1], 1)
        for k, v in enumerate(vs):
            if k != n:
                values *= v[at[k]]
        out = np.zeros((core.shape[n], vs[0].shape[1]))
        np.add.at(out, at[n], values)
        return out
    if how != "contract":
        raise ValueError(f"unknown way {how!r}")
    x = np.moveaxis(core, n, -1)
    others = [v for k, v in enumerate(vs) if k != n]
    # The first contraction is one matrix product; the rest keep the component index.
    y = np.tensordot(others[0], x, (0, 0))
    for v in others[1:]:
        y = np.einsum("ra...,ar->r...", y, v)
    return y.T


def shared_mttkrp(core: np.ndarray, vs: Sequence[np.ndarray]) -> list[np.ndarray]:
    """core_mttkrp of every mode with the same matrices: a contraction over leading modes serves all modes behind them."""
    out, left = [], None
    for k in range(core.ndim):
        if left is None:
            out.append(core_mttkrp(core, vs, 0))
            left = np.tensordot(vs[0], core, (0, 0))
            continue
        x = left
        for v in reversed(vs[k + 1 :]):
            x = np.einsum("r...a,ar->r...", x, v)
        out.append(x.T.copy())
        if k + 1 < core.ndim:
            left = np.einsum("ra...,ar->r...", left, vs[k])
    return out


# Cells and factor rows as DataFrames ----------------------------------------------------------------------------


def rows_frame(spark: SparkSession, m: np.ndarray, name: str = "f") -> DataFrame:
    """Rows (i, f) of a matrix."""
    return spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(m)], f"i long, {name} array<double>")


def formula_rows(spark: SparkSession, size: int, rank: int) -> DataFrame:
    """The integer test matrix u(i, r) = ((7 i + 3 r) mod 5) - 2."""
    return spark.range(size).select(F.col("id").alias("i"), F.array(*[((F.col("id") * 7 + 3 * r) % 5 - 2).cast("double") for r in range(rank)]).alias("f"))


def _joined(cells: DataFrame, rows: DataFrame, n: int, name: str) -> DataFrame:
    own = rows.select(F.col("i").alias(f"i{n + 1}"), F.col("f").alias(name))
    return cells.join(own, f"i{n + 1}")


def _sums(product: Sequence[Column], names: Sequence[str]) -> list[Column]:
    return [F.sum(p).alias(name) for p, name in zip(product, names, strict=True)]


def ttm(cells: DataFrame, rows: DataFrame, n: int, rank: int) -> DataFrame:
    """Cells of the n-mode product with the transpose of a factor: index n becomes the component.

    One sum for each component over the other coordinates (partial sums before the exchange), then a projection to cells.
    """
    names = [f"_{r}" for r in range(rank)]
    others = [c for c in modes_of(cells) if c != f"i{n + 1}"]
    wide = _joined(cells, rows, n, "f").groupBy(*others).agg(*_sums([F.col("v") * F.col("f")[r] for r in range(rank)], names))
    long = wide.select(*others, F.posexplode(F.array(*names)).alias("_r", "v"))
    return long.select(*[F.col("_r").cast("long").alias(c) if c == f"i{n + 1}" else F.col(c) for c in modes_of(cells)], "v")


def ttm_chain(cells: DataFrame, factors: Sequence[tuple[DataFrame, int]], skip: int | None = None, sizes: Sequence[int] | None = None) -> DataFrame:
    """n-mode products with all factors but one, the one that shrinks most first when sizes are known."""
    order = [k for k in range(len(factors)) if k != skip]
    if sizes:
        order.sort(key=lambda k: factors[k][1] / sizes[k])
    for k in order:
        cells = ttm(cells, factors[k][0], k, factors[k][1])
    return cells


def mttkrp(cells: DataFrame, factors: Sequence[DataFrame], n: int, rank: int, strategy: str = "auto") -> DataFrame:
    """(i, r, v) of the unfolding times the Khatri-Rao product, which is never built.

    wide: one sum a component, all at once; columnwise: components are rows, nonzeros only, for ranks beyond what one
    generated function holds.
    """
    own = f"i{n + 1}"
    met = cells
    for k, f in enumerate(factors):
        if k != n:
            met = _joined(met, f, k, f"f{k}")
    others = [k for k in range(len(factors)) if k != n]
    if strategy == "auto":
        strategy = "wide" if rank <= 32 else "columnwise"
    if strategy == "columnwise":
        each = met.select(own, "v", *[f"f{k}" for k in others], F.explode(F.sequence(F.lit(0), F.lit(rank - 1))).alias("r"))
        value = reduce(lambda a, k: a * F.get(F.col(f"f{k}"), F.col("r")), others, F.col("v"))
        return each.groupBy(F.col(own).alias("i"), "r").agg(F.sum(value).alias("v"))
    names = [f"_{r}" for r in range(rank)]
    product = [reduce(lambda a, k, r=r: a * F.col(f"f{k}")[r], others, F.col("v")) for r in range(rank)]
    wide = met.groupBy(F.col(own).alias("i")).agg(*_sums(product, names))
    return wide.select("i", F.posexplode(F.array(*names)).alias("r", "v"))


def gram(rows: DataFrame, rank: int, other: DataFrame | None = None, other_rank: int | None = None) -> np.ndarray:
    """AtA, or AtB for rows of another factor: wide sums, so only the small matrix reaches the driver."""
    b, m = ("f", rank) if other is None else ("g", other_rank or rank)
    met = rows if other is None else rows.join(other.select("i", F.col("f").alias("g")), "i")
    sums = met.agg(*[F.sum(F.col("f")[r] * F.col(b)[s]).alias(f"_{r}_{s}") for r in range(rank) for s in range(m)]).first()
    return np.array([float(x or 0) for x in sums]).reshape(rank, m)


def sketch_rows(cells: DataFrame, n: int, rank: int, seed: int, dist: str = "gaussian") -> DataFrame:
    """Rows (i, f) of the unfolding times a random matrix that exists only as an expression of its coordinates."""
    own, others = f"i{n + 1}", [F.col(c) for c in modes_of(cells) if c != f"i{n + 1}"]
    number = gauss_col if dist == "gaussian" else sign_col
    names = [f"_{r}" for r in range(rank)]
    wide = cells.groupBy(F.col(own).alias("i")).agg(*_sums([F.col("v") * number(seed, [*others, F.lit(r)]) for r in range(rank)], names))
    return wide.select("i", F.array(*names).alias("f"))


def sketch(cells: DataFrame, n: int, rank: int, seed: int, dist: str = "gaussian") -> DataFrame:
    """sketch_rows() as (i, r, v)."""
    return sketch_rows(cells, n, rank, seed, dist).select("i", F.posexplode("f").alias("r", "v"))


def norm2(cells: DataFrame) -> float:
    return float(cells.agg(F.sum(F.col("v") * F.col("v"))).first()[0] or 0)


def inner(a: DataFrame, b: DataFrame) -> float:
    return float(a.join(b.withColumnRenamed("v", "w"), modes_of(a)).agg(F.sum(F.col("v") * F.col("w"))).first()[0] or 0)


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    """Cells of the difference; a cell that one side lacks is zero there."""
    met = a.join(b.withColumnRenamed("v", "w"), modes_of(a), "full")
    return met.select(*modes_of(a), (F.coalesce("v", F.lit(0.0)) - F.coalesce("w", F.lit(0.0))).alias("v"))


def outer(vectors: Sequence[DataFrame]) -> DataFrame:
    """Cells of the rank-one tensor of vectors (i, v); for tests and small syntheses."""
    out = None
    for k, x in enumerate(vectors):
        own = x.select(F.col("i").alias(f"i{k + 1}"), F.col("v").alias(f"_v{k}"))
        out = own if out is None else out.crossJoin(own)
    value = reduce(lambda a, k: a * F.col(f"_v{k}"), range(1, len(vectors)), F.col("_v0"))
    return out.select(*[f"i{k + 1}" for k in range(len(vectors))], value.alias("v"))


def reconstruct(cells: DataFrame, factors: Sequence[DataFrame], rank: int, weights: Sequence[float] | None = None) -> DataFrame:
    """The CP model's value at given cells, as `w` beside them."""
    met = cells
    for k, f in enumerate(factors):
        met = _joined(met, f, k, f"f{k}")
    terms = [reduce(lambda a, k, r=r: a * F.col(f"f{k}")[r], range(len(factors)), F.lit(float(weights[r]) if weights is not None else 1.0)) for r in range(rank)]
    return met.select(*cells.columns, reduce(lambda a, b: a + b, terms).alias("w"))


def multilinear_rank(x: np.ndarray, tol: float = 1e-9) -> tuple[int, ...]:
    """Numerical rank of each unfolding, by the eigenvalues of its Gram."""
    out = []
    for n in range(x.ndim):
        m = unfold_dense(x, n)
        w = np.linalg.eigvalsh(m @ m.T)
        out.append(int((w > tol * w.max(initial=0)).sum()))
    return tuple(out)
