"""Tucker form: deterministic, alternating, sampled and sketched ways to get it, all from the sums that tensors offer."""

from __future__ import annotations

import json
from collections.abc import Sequence
from dataclasses import dataclass, field
from math import prod

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.counter import draw, gauss, mix_col, P
from .algebra import fold_dense, multiply_all, unfold_dense
from .orth import orth
from .tall import Drawn
from .tensors import DRIVER_NUMBERS, BlockTensor, CooTensor, Tensor

CORE_LIMIT = 200_000_000


@dataclass
class TuckerModel:
    """core (small, on the driver) and one orthonormal factor for each mode."""

    core: np.ndarray
    factors: list[np.ndarray]
    norm2: float | None = None  # of the tensor it stands for
    stats: dict = field(default_factory=dict)

    @property
    def ranks(self) -> tuple[int, ...]:
        return self.core.shape

    def fit(self) -> float:
        """1 - |Y - model| / |Y|, from norms alone (orthonormal factors, core = projection)."""
        return 1 - float(np.sqrt(max(0.0, self.norm2 - (self.core**2).sum()) / self.norm2))

    def dense(self) -> np.ndarray:
        return multiply_all(self.core, self.factors)

    def features(self, mode: int) -> np.ndarray:
        """Samples of a mode in the coordinates of its factor, scaled by the energy of each component."""
        return self.factors[mode] * np.sqrt((unfold_dense(self.core, mode) ** 2).sum(1))

    def truncate(self, ranks: Sequence[int]) -> TuckerModel:
        """Leading part by an HOSVD of the core: takes oversampling away."""
        bases = []
        for n, r in enumerate(ranks):
            m = unfold_dense(self.core, n)
            bases.append(np.linalg.eigh(m @ m.T)[1][:, ::-1][:, : min(r, m.shape[0])])
        return TuckerModel(multiply_all(self.core, bases, transpose=True), [u @ b for u, b in zip(self.factors, bases, strict=True)], self.norm2, dict(self.stats))

    def rotate(self, turns: Sequence[np.ndarray]) -> TuckerModel:
        """The same tensor in other bases: U Q and the core times the transposes."""
        return TuckerModel(multiply_all(self.core, turns, transpose=True), [u @ q for u, q in zip(self.factors, turns, strict=True)], self.norm2, dict(self.stats))

    @classmethod
    def from_cp(cls, factors: Sequence[np.ndarray]) -> TuckerModel:
        """The form of a tensor known by its CP factors; no cell is ever made."""
        from .algebra import cp_dense

        bases, small = zip(*(np.linalg.qr(a) for a in factors), strict=True)
        core = cp_dense(small)
        return cls(core, list(bases), float((core**2).sum()), {"passes": 0})

    def save(self, spark: SparkSession, path: str) -> None:
        for n, u in enumerate(self.factors):
            spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(u)], "i long, f array<double>").write.mode("overwrite").parquet(f"{path}/factor_{n}")
        meta = json.dumps({"core": self.core.ravel().tolist(), "shape": self.core.shape, "norm2": self.norm2, "stats": self.stats})
        spark.createDataFrame([(meta,)], "meta string").coalesce(1).write.mode("overwrite").parquet(f"{path}/core")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> TuckerModel:
        meta = json.loads(spark.read.parquet(f"{path}/core").first()["meta"])
        core = np.array(meta["core"]).reshape(meta["shape"])
        factors = []
        for n in range(core.ndim):
            rows = spark.read.parquet(f"{path}/factor_{n}").collect()
            u = np.zeros((len(rows), core.shape[n]))
            for r in rows:
                u[r["i"]] = r["f"]
            factors.append(u)
        return cls(core, factors, meta["norm2"], meta["stats"])


def sketch_sizes(shape: Sequence[int], ranks: Sequence[int], oversample: int) -> list[int]:
    """Ranks with oversampling, clipped to the mode's size and to what the other modes can span."""
    sizes = [min(r + oversample, s) for r, s in zip(ranks, shape, strict=True)]
    return [min(r, prod(x for k, x in enumerate(sizes) if k != n)) for n, r in enumerate(sizes)]


def _leading(gram: np.ndarray, rank: int) -> np.ndarray:
    return np.linalg.eigh(gram)[1][:, ::-1][:, :rank]


def _first(t: Tensor, n: int, rank: int) -> np.ndarray:
    """Leading left singular vectors of unfolding n, by whichever Gram belongs on the driver."""
    long = isinstance(t, BlockTensor) and (n == t.tall or t.shape[n] ** 2 > DRIVER_NUMBERS)
    u = t.leading(n, min(rank, t.shape[n])) if long else None
    return _leading(t.gram(n), min(rank, t.shape[n])) if u is None else u


def _core(x: np.ndarray, shape: Sequence[int], n: int) -> np.ndarray:
    if prod(shape) > CORE_LIMIT:
        raise ValueError(f"a core of {prod(shape)} cells doesn't belong on the driver")
    return fold_dense(x, shape, n)


def sketch_tucker(t: Tensor, ranks: Sequence[int], oversample: int = 10, method: str = "two_sweep", sweeps: int = 2, seed: int = 1, mode_order: Sequence[int] | None = None, reduce: str = "eager", how: str = "gram", dist: str = "gaussian", power: int = 0, init: str = "random", truncate: bool = False, omega: str = "counter") -> TuckerModel:
    """Randomised Tucker.

    sequential: for each mode sketch the unfolding, take a basis of the sketch, shrink the tensor by it and go on.
    two_sweep: from Gaussian starting matrices, `sweeps` rounds of projecting on all other modes and sketching what is
    left; the last projection also gives the core. Modes whose sketch would be as wide as the mode keep the identity.
    power: times that a sketch is multiplied by what it was taken from and its transpose, which turns the basis to the leading
    directions under noise. With two_sweep that is the small projection, so no pass is added; with sequential each costs a Gram.
    """
    reads, norm2, sizes = t.passes.reads, None, sketch_sizes(t.shape, ranks, oversample)
    if method == "sequential":
        order = list(mode_order or sorted(range(t.order), key=lambda n: sizes[n] / t.shape[n]))
        factors: list[np.ndarray | None] = [np.eye(s) if sizes[n] >= s or n not in order else None for n, s in enumerate(t.shape)]
        norm2, x = t.norm2(), t
        for n in order:
            if sizes[n] >= t.shape[n]:
                continue
            if omega == "broadcast" and isinstance(x, BlockTensor):
                full = prod(s for k, s in enumerate(x.shape) if k != n)
                z = x.sketch(n, sizes[n], seed + 101 * n, dist, np.random.default_rng(seed + n).standard_normal((full, sizes[n])))
            else:
                z = x.sketch(n, sizes[n], seed + 101 * n, dist)
            for _ in range(power):
                z = x.gram(n) @ z
            factors[n] = orth(z, how)
            x = (x.shrink(n, factors[n], reduce) if isinstance(x, BlockTensor) else x.shrink(n, factors[n])).kept()
        core = x.dense()
    elif method == "two_sweep":
        order = list(mode_order or range(t.order))
        factors = [np.eye(s) if sizes[n] >= s else Drawn(s, sizes[n], seed + 7 * n) if n == t.tall else gauss(seed + 7 * n, np.ix_(np.arange(s), np.arange(sizes[n]))) for n, s in enumerate(t.shape)]
        if init == "sequential":
            first = sketch_tucker(t, ranks, oversample, "sequential", seed=seed, how=how)
            factors, norm2 = first.factors, first.norm2
        norm2 = t.norm2() if norm2 is None else norm2
        for sweep in range(sweeps):
            for n in order:
                last = sweep == sweeps - 1 and n == order[-1]
                inner = [f.shape[1] for k, f in enumerate(factors) if k != n]
                small = draw(dist, seed + 1000 * (sweep + 1) + n, np.ix_(np.arange(prod(inner)), np.arange(sizes[n])))
                if not last:
                    if sizes[n] < t.shape[n] and not power:
                        factors[n] = orth(t.project(n, factors, small), how)
                    elif sizes[n] < t.shape[n]:  # the projection is small enough to be multiplied by again, no pass is added
                        x = t.project(n, factors)
                        z = x @ small
                        for _ in range(power):
                            z = x @ (x.T @ z)
                        factors[n] = orth(z, how)
                    continue
                x = t.project(n, factors)
                if sizes[n] < t.shape[n]:
                    z = x @ small
                    for _ in range(power):
                        z = x @ (x.T @ z)
                    factors[n] = orth(z, how)
                core = _core(factors[n].T @ x, [f.shape[1] for f in factors], n)
    else:
        raise ValueError(f"unknown method {method!r}")
    model = TuckerModel(core, factors, norm2, {"passes": t.passes.reads - reads - 1, "sizes": [f.shape[1] for f in factors]})
    return model.truncate(ranks) if truncate else model


def sketch_tucker_rows(t: CooTensor, ranks: Sequence[int], oversample: int = 10, seed: int = 1, how: str = "gram", mode_order: Sequence[int] | None = None) -> tuple[list[DataFrame], np.ndarray]:
    """The sequential sketch for modes of any length: bases are rows (i, f) that never leave the executors; the core is returned.

    A sketch is one sum of cells by index, its basis a Gram of the rows and a projection, and the tensor shrinks by a join with
    the basis rows. Only Grams and the core are on the driver. Rows without any cell are absent (their basis row is zero).
    """
    from ..sources.storage import stored
    from .algebra import sketch_rows, ttm
    from .orth import orth_rows

    sizes = sketch_sizes(t.shape, ranks, oversample)
    bases: list[DataFrame | None] = [None] * t.order
    x = t
    for n in mode_order or sorted(range(t.order), key=lambda n: sizes[n] / t.shape[n]):
        z = stored(sketch_rows(x.df, n, sizes[n], seed + 101 * n))
        bases[n] = stored(orth_rows(z, how))
        width = len(bases[n].first()["f"])
        t.passes.reads += 2
        x = CooTensor(ttm(x.df, bases[n], n, width), tuple(width if k == n else s for k, s in enumerate(x.shape)), t.passes).kept()
    return bases, x.dense()


def hosvd(t: Tensor, ranks: Sequence[int], sequential: bool = False) -> TuckerModel:
    """Leading eigenvectors of the Gram of each unfolding, of the tensor itself or of what earlier modes left."""
    reads, norm2, factors, x = t.passes.reads, t.norm2(), [], t
    for n, r in enumerate(ranks):
        factors.append(_first(x, n, r))
        if sequential:
            x = x.shrink(n, factors[-1]).kept()
    core = x.dense() if sequential else _core(factors[-1].T @ t.project(t.order - 1, factors), [f.shape[1] for f in factors], t.order - 1)
    return TuckerModel(core, factors, norm2, {"passes": t.passes.reads - reads - 1})


def tucker_als(t: Tensor, ranks: Sequence[int], iters: int = 2, init: str = "hosvd", tol: float = 0.0, seed: int = 1) -> TuckerModel:
    """Each mode in turn: project on all others, leading singular vectors."""
    reads, norm2 = t.passes.reads, t.norm2()
    if init == "hosvd":
        factors = [_first(t, n, r) for n, r in enumerate(ranks)]
    else:
        factors = [orth(gauss(seed + n, np.ix_(np.arange(s), np.arange(min(r, s))))) for n, (s, r) in enumerate(zip(t.shape, ranks, strict=True))]
    energy, history = 0.0, []
    for _ in range(iters):
        for n, r in enumerate(ranks):
            wide = t.shape[n] * prod(f.shape[1] for k, f in enumerate(factors) if k != n) > DRIVER_NUMBERS and n < t.order - 1
            u = t.leading(n, min(r, t.shape[n]), factors) if isinstance(t, BlockTensor) and (wide or n == t.tall) else None
            if u is not None:
                factors[n] = u
                if n < t.order - 1:
                    continue
            x = t.project(n, factors)
            if u is None:
                factors[n] = np.linalg.svd(x, full_matrices=False)[0][:, : min(r, t.shape[n])]
        core = _core(factors[-1].T @ x, [f.shape[1] for f in factors], t.order - 1)
        now = float((core**2).sum())
        history.append(1 - float(np.sqrt(max(0.0, norm2 - now) / norm2)))
        if now - energy <= tol * norm2 and tol:
            break
        energy = now
    return TuckerModel(core, factors, norm2, {"passes": t.passes.reads - reads - 1, "history": history})


def entry_sample_tucker(t: CooTensor, ranks: Sequence[int], q: float, seed: int = 1, **options) -> TuckerModel:
    """Keep each cell with probability q, divided by q, then go on as with the whole; which cells follows from the seed."""
    coords = [F.col(f"i{k + 1}") for k in range(t.order)]
    kept = t.df.filter(mix_col(seed, coords) < int(q * P)).withColumn("v", F.col("v") / q)
    model = hosvd(CooTensor(kept, t.shape, t.passes).kept(), ranks) if not options else tucker_als(CooTensor(kept, t.shape, t.passes).kept(), ranks, **options)
    # The core belongs to the tensor itself.
    x = t.project(t.order - 1, model.factors)
    return TuckerModel(_core(model.factors[-1].T @ x, model.ranks, t.order - 1), model.factors, t.norm2(), model.stats)


def fiber_sample_tucker(t: CooTensor, ranks: Sequence[int], n_fibers: int, p: str = "norm2", seed: int = 1) -> TuckerModel:
    """A basis for each mode from sampled columns of its unfolding, drawn in proportion to squared norm, or evenly."""
    factors = []
    for n, r in enumerate(ranks):
        others = [f"i{k + 1}" for k in range(t.order) if k != n]
        fibers = t.df.groupBy(*others).agg(F.sum(F.col("v") * F.col("v")).alias("w"))
        # Weighted sampling without replacement: the smallest -ln(u) / w win.
        u = (mix_col(seed + n, [F.col(c) for c in others]) + F.lit(0.5)) / float(P)
        chosen = fibers.filter("w > 0").orderBy(-F.ln(u) / (F.col("w") if p == "norm2" else F.lit(1.0)), *others).limit(n_fibers)
        numbered = chosen.withColumn("c", F.row_number().over(Window.orderBy(*others)) - 1)
        m = np.zeros((t.shape[n], n_fibers))
        for row in t.df.join(F.broadcast(numbered), others).select(f"i{n + 1}", "c", F.col("v") / F.sqrt("w")).collect():
            m[row[0], row[1]] += row[2]
        u_, s, _ = np.linalg.svd(m, full_matrices=False)
        factors.append(u_[:, : min(r, int((s > 1e-9 * s.max(initial=0)).sum()))])
    x = t.project(t.order - 1, factors)
    return TuckerModel(_core(factors[-1].T @ x, [f.shape[1] for f in factors], t.order - 1), factors, t.norm2())


def tucker_error_bound(t: Tensor, ranks: Sequence[int]) -> tuple[float, float]:
    """(largest tail, sum of tails) of the unfoldings' spectra: squared error of the truncated HOSVD lies between."""
    tails = []
    for n, r in enumerate(ranks):
        w = np.sort(np.linalg.eigvalsh(t.gram(n)))[::-1]
        tails.append(float(np.maximum(w[r:], 0).sum()))
    return max(tails), sum(tails)


def factor_frame(spark: SparkSession, model, mode: int) -> DataFrame:
    """Rows (i, r, v) of a factor."""
    rows = [(i, r, float(x)) for i, row in enumerate(model.factors[mode]) for r, x in enumerate(row)]
    return spark.createDataFrame(rows, "i long, r int, v double")
