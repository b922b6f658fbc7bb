"""Accuracy and cost measures."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algebra import gram_hadamard, multiply_all, unfold_dense
from .cluster import assignment
from .cp import CPModel
from .tall import inner as product
from .tensors import Tensor
from .tucker import TuckerModel


def model_norm2(model) -> float:
    if isinstance(model, CPModel):
        return model.norm2()
    grams = [u.T @ u for u in model.factors]
    return float((model.core * multiply_all(model.core, grams)).sum())


def model_inner(a, b) -> float:
    """Inner product of two models from small matrices; no cell is made."""
    if isinstance(a, CPModel) and isinstance(b, CPModel):
        return float(gram_hadamard([x.T @ y for x, y in zip(a.absorbed(), b.absorbed(), strict=True)]).sum())
    if isinstance(a, CPModel):
        return model_inner(b, a)
    if isinstance(b, CPModel):
        from .algebra import cp_dense

        return float((a.core * cp_dense([u.T @ f for u, f in zip(a.factors, b.absorbed(), strict=True)])).sum())
    return float((a.core * multiply_all(b.core, [u.T @ w for u, w in zip(a.factors, b.factors, strict=True)])).sum())


def fit_models(truth, model) -> float:
    """Fit to a truth that is itself a model."""
    total = model_norm2(truth)
    return 1 - float(np.sqrt(max(0.0, total - 2 * model_inner(truth, model) + model_norm2(model)) / total))


def fit(t: Tensor, model, total: float | None = None) -> float:
    """Fit to all cells of a tensor, zeros included, in one pass. total: its squared norm, where that is known."""
    total = t.norm2() if total is None else total
    if isinstance(model, CPModel):
        fs, n = model.absorbed(), t.order - 1 if t.tall is None else t.tall
        inner = product(fs[n], t.mttkrp(fs, n))
    elif t.tall is not None:  # so the rows of the tall factor stay on the driver
        inner = product(model.factors[t.tall], t.project(t.tall, model.factors, unfold_dense(model.core, t.tall).T))
    else:
        x = t.project(t.order - 1, model.factors)
        inner = float((model.factors[-1].T @ x * unfold_dense(model.core, t.order - 1)).sum())
    return 1 - float(np.sqrt(max(0.0, total - 2 * inner + model_norm2(model)) / total))


def fit_compressed(form: TuckerModel, model: CPModel) -> float:
    """Fit to the compact form: what the iteration watches."""
    return fit_models(form, model)


def fit_tucker(norm2: float, core: np.ndarray) -> float:
    return 1 - float(np.sqrt(max(0.0, norm2 - (core**2).sum()) / norm2))


def _standard(a: np.ndarray) -> np.ndarray:
    a = a - a.mean(0)
    return a / np.maximum(a.std(0), 1e-300)


def sir(true: np.ndarray, found: np.ndarray) -> np.ndarray:
    """Signal to interference (dB) of each true component against its match, after standardising and fixing signs."""
    a, b = _standard(true), _standard(found)
    c = a.T @ b / len(a)
    match = assignment(-np.abs(c)) if c.shape[0] <= c.shape[1] else np.abs(c).argmax(1)
    b = b[:, match] * np.sign(c[np.arange(len(match)), match])
    return 20 * np.log10(np.linalg.norm(a, axis=0) / np.maximum(np.linalg.norm(a - b, axis=0), 1e-15))


def snr_db(truth2: float, noise2: float) -> float:
    return float(10 * np.log10(truth2 / noise2))


def sparsity(a: np.ndarray) -> float:
    """Share of zero entries."""
    return float((a == 0).mean())


def density(t) -> float:
    """Share of cells that are stored and not zero."""
    return float(t.df.filter("v <> 0").count() / np.prod([float(s) for s in t.shape]))


def monte_carlo(spark: SparkSession, run: Callable[[int], dict], seeds: Sequence[int], failed: float = 0.5) -> DataFrame:
    """Mean, deviation and failures (fit under `failed`) of a run over seeds, for each method it reports."""
    rows = [(str(m), int(s), float(v)) for s in seeds for m, v in run(s).items()]
    df = spark.createDataFrame(rows, "method string, seed int, fit double")
    return df.groupBy("method").agg(F.avg("fit").alias("mean_fit"), F.stddev_samp("fit").alias("sd_fit"), F.count("*").alias("runs"), F.sum((F.col("fit") < failed).cast("int")).alias("failures"))


def log_slope(sizes: Sequence[float], seconds: Sequence[float]) -> float:
    """Exponent of a power law through measured times."""
    return float(np.polyfit(np.log(sizes), np.log(seconds), 1)[0])
