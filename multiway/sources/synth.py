"""Planted tensors: factors read from the tables, cells made where they are needed, noise that follows from a seed."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.algebra import cp_dense, gram_hadamard, multiply_all
from ..operators.cp import CPModel
from ..functions.counter import P, gauss, mix_col, uniform
from ..operators.tensors import BlockTensor, generated, plan_grid
from ..operators.tucker import TuckerModel
from .tables import table


def normal_factors(spark: SparkSession, sf_dir: str, order: int, size: int, rank: int, integer: bool = False) -> list[np.ndarray]:
    """Entries of embeddings, scaled to unit variance (or to small integers)."""
    if order * rank > 64:
        raise ValueError("the embeddings have 64 numbers each")
    rows = table(spark, sf_dir, "embeddings").filter(F.col("vec_id") < size).select("vec_id", "embedding").orderBy("vec_id").collect()
    if len(rows) < size:
        raise ValueError(f"there are {len(rows)} vectors only")
    e = np.array([r["embedding"] for r in rows], float)
    e = np.floor(12 * e + 0.5) if integer else 8 * e
    return [e[:, rank * n : rank * (n + 1)] for n in range(order)]


def placed(rows: DataFrame, need: int) -> np.ndarray:
    """Numbers of rows (place, number) with the places 0 to need - 1, in order; they travel as columns, never as row objects."""
    met = rows.toArrow()
    places = met.column(0).to_numpy()
    out, seen = np.zeros(need), np.zeros(need, bool)
    if len(places) == need and places.min(initial=0) >= 0 and places.max(initial=0) < need:
        seen[places] = True
        out[places] = met.column(1).to_numpy()
    if not seen.all():
        raise ValueError(f"{need} numbers with the places 0 to {need - 1} are needed, there are {len(places)} rows")
    return out


def exponential_factors(spark: SparkSession, sf_dir: str, order: int, size: int, rank: int, zeros: int = 10, integer: bool = False) -> list[np.ndarray]:
    """Event values (exponential with mean 10, or small integers), one in `zeros` set to zero by a rule."""
    need = order * size * rank
    events = table(spark, sf_dir, "events").filter((F.col("event_id") < need) & F.col("value").isNotNull())
    v = placed(events.select(F.col("event_id").cast("long"), F.col("value").cast("double")), need).reshape(order, size, rank)
    if integer:
        v = np.floor(v / 40)
    else:
        v /= 5
    v[:, _zero(size, rank, zeros)] = 0
    return list(v)


def order_factors(spark: SparkSession, sf_dir: str, order: int, rank: int, zeros: int = 5, seed: int = 70) -> list[np.ndarray]:
    """Exponential with mean 10, drawn by key, customer and price (in cents) of each order, in order of the keys; one in `zeros` set to zero by a rule.

    As long as all orders reach; those without a key, a customer or a finite price take no part. Executors sort them, only the numbers travel.
    """
    cents = F.round(F.col("o_totalprice") * 100).try_cast("long")
    drawn = -10 * F.ln((mix_col(seed, [F.col("o_orderkey"), F.col("o_custkey"), cents]) + F.lit(0.5)) / F.lit(float(P)))
    rows = table(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("k"), drawn.alias("v")).dropna()
    met = rows.orderBy("k", "v").select("v").toArrow()
    size = met.num_rows // (order * rank)
    if not size:
        raise ValueError(f"{order * rank} orders are needed, there are {met.num_rows}")
    v = np.concatenate([c.to_numpy() for c in met.column(0).chunks])[: order * size * rank].reshape(order, size, rank)
    v[:, _zero(size, rank, zeros)] = 0
    return list(v)


def _zero(size: int, rank: int, zeros: int) -> np.ndarray:
    """Which entries of a factor are zero: one in `zeros`, by a rule."""
    i, r = np.arange(size)[:, None], np.arange(rank)[None]
    return (31 * i + 17 * r + 7 * (i // 11)) % zeros == 0


def drawn_factors(order: int, size: int, rank: int, kind: str = "normal", zeros: int = 10, seed: int = 900) -> list[np.ndarray]:
    """Factors from counters, for sizes beyond what a small table holds: standard normal, or exponential with mean 10 and zeros."""
    axes, out = np.ix_(np.arange(size), np.arange(rank)), []
    for n in range(order):
        if kind == "normal":
            out.append(gauss(seed + n, axes))
        else:
            v = -10 * np.log1p(-uniform(seed + n, axes))
            v[_zero(size, rank, zeros)] = 0
            out.append(v)
    return out


def sigma_for(norm2: float, cells: float, snr: float | None) -> float:
    return 0.0 if snr is None else float(np.sqrt(norm2 / cells * 10 ** (-snr / 10)))


def cp_tensor(spark: SparkSession, factors: Sequence[np.ndarray], snr: float | None = None, grid: Sequence[int] | None = None, seed: int = 1) -> tuple[BlockTensor, CPModel]:
    """Blocks of a CP model plus noise at an SNR in dB, and the model."""
    shape = [f.shape[0] for f in factors]
    least = plan_grid(shape)
    grid = grid or [max(min(4, shape[0]), least[0]), *least[1:]]
    norm2 = float(gram_hadamard([f.T @ f for f in factors]).sum())

    def make(lo: list[int], dims: list[int]) -> np.ndarray:
        return cp_dense([f[a : a + d] for f, a, d in zip(factors, lo, dims, strict=True)])

    return generated(spark, shape, grid, make, sigma_for(norm2, prod(map(float, shape)), snr), seed), CPModel(list(factors))


def tucker_tensor(spark: SparkSession, sf_dir: str, size: int, rank: int, snr: float | None = None, grid: Sequence[int] | None = None, seed: int = 1) -> tuple[BlockTensor, TuckerModel]:
    """A planted 3-way Tucker tensor from embeddings."""
    us = normal_factors(spark, sf_dir, 3, size, rank)
    need = 200 + 11 * rank
    rows = {r["vec_id"]: r["embedding"] for r in table(spark, sf_dir, "embeddings").filter((F.col("vec_id") >= 200) & (F.col("vec_id") < need)).select("vec_id", "embedding").collect()}
    core = np.array([[[8 * rows[200 + 10 * a + b][40 + c] for c in range(rank)] for b in range(rank)] for a in range(rank)])
    form = TuckerModel(core, us)
    grams = [u.T @ u for u in us]
    form.norm2 = float((core * multiply_all(core, grams)).sum())

    def make(lo: list[int], dims: list[int]) -> np.ndarray:
        return multiply_all(core, [u[a : a + d] for u, a, d in zip(us, lo, dims, strict=True)])

    return generated(spark, [size] * 3, grid or (4, 1, 1), make, sigma_for(form.norm2, float(size) ** 3, snr), seed), form


def model_cells(spark: SparkSession, model, rounded: bool = True) -> DataFrame:
    """Cells i1.., v of a model, made slice by slice of the first mode."""
    fs = model.absorbed() if isinstance(model, CPModel) else model.factors
    core = None if isinstance(model, CPModel) else model.core
    shape = [f.shape[0] for f in fs]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                own = [fs[0][i : i + 1], *fs[1:]]
                x = cp_dense(own) if core is None else multiply_all(core, own)
                at = np.indices(x.shape).reshape(x.ndim, -1)
                at[0] += i
                v = x.ravel()
                value = pa.array(np.rint(v).astype(np.int64)) if rounded else pa.array(v)
                yield pa.RecordBatch.from_arrays([*(pa.array(c.astype(np.int64)) for c in at), value], [*[f"i{k + 1}" for k in range(len(shape))], "v"])

    schema = ", ".join([*[f"i{k + 1} long" for k in range(len(shape))], "v long" if rounded else "v double"])
    return spark.range(shape[0]).mapInArrow(run, schema)
