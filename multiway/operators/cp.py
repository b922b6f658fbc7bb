"""CP decompositions. One loop serves all of them: what differs is where the gradient's data term comes from.

A source answers `mttkrp(factors, n)` and `norm2`. The tensor itself is a source (each call a pass over the data: the direct
baselines); its Tucker form is another (calls cost a few small products: the compressed method, no pass at all).
"""

from __future__ import annotations

import time
from collections.abc import Sequence
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..functions.counter import gauss, uniform
from .algebra import core_mttkrp, cp_dense, gram_hadamard, shared_mttkrp, unfold_dense
from .constraints import FREE, Constraint, nonneg, per_mode
from .tall import Tall
from .tensors import Tensor
from .tucker import TuckerModel

UPDATES = ("als", "mu", "hals", "pg")
#: Rows of a factor that are updated at a time: with their basis they fit a core's cache.
BLOCK_ROWS = 4096


@dataclass
class CPModel:
    factors: list[np.ndarray]
    weights: np.ndarray | None = None
    history: list[float] = field(default_factory=list)
    stats: dict = field(default_factory=dict)

    @property
    def rank(self) -> int:
        return self.factors[0].shape[1]

    def absorbed(self, mode: int = -1) -> list[np.ndarray]:
        """Factors with the weights moved into one of them."""
        out = [f.copy() for f in self.factors]
        if self.weights is not None:
            out[mode] = out[mode] * self.weights
        return out

    def normalise(self) -> CPModel:
        """Unit columns, heaviest component first, largest entry positive in all modes but the last."""
        fs = self.absorbed()
        norms = [np.maximum(np.linalg.norm(f, axis=0), 1e-300) for f in fs]
        weights = reduce(np.multiply, norms)
        fs = [f / n for f, n in zip(fs, norms, strict=True)]
        for f in fs[:-1]:
            s = np.sign(f[np.abs(f).argmax(0), np.arange(f.shape[1])])
            s[s == 0] = 1
            f *= s
            fs[-1] *= s
        by = np.argsort(-weights, kind="stable")
        return CPModel([f[:, by] for f in fs], weights[by], self.history, self.stats)

    def dense(self) -> np.ndarray:
        return cp_dense(self.absorbed())

    def norm2(self) -> float:
        return float(gram_hadamard([f.T @ f for f in self.absorbed()]).sum())


class TuckerSource:
    """Gradients from the compact form: U (core times the small matrices UtA)."""

    def __init__(self, form: TuckerModel, how: str = "contract"):
        self.form, self.how, self.shape = form, how, tuple(u.shape[0] for u in form.factors)
        self.small: list[np.ndarray | None] = [None] * len(self.shape)
        self.seen: list[np.ndarray | None] = [None] * len(self.shape)

    def _vs(self, factors: Sequence[np.ndarray]) -> list[np.ndarray]:
        for n, (u, a) in enumerate(zip(self.form.factors, factors, strict=True)):
            if self.seen[n] is not a:  # only the factor that moved since is multiplied again
                self.small[n], self.seen[n] = u.T @ a, a
        return self.small

    def mttkrp(self, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
        vs = self._vs(factors)
        h = shared_mttkrp(self.form.core, vs)[n] if self.how == "reuse" else core_mttkrp(self.form.core, vs, n, self.how)
        return self.form.factors[n] @ h

    def norm2(self) -> float:
        return float((self.form.core**2).sum())


class ReuseSource:
    """A tensor whose modes' gradients share readings: one pass contracts the later modes for the first ones, another the
    first for the later ones; two passes a sweep instead of one for each mode."""

    def __init__(self, t: Tensor):
        self.t, self.shape, self.split = t, t.shape, (t.order + 1) // 2
        self.half: dict[int, np.ndarray] = {}

    def mttkrp(self, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
        first = n < self.split
        if n in (0, self.split):
            self.half[first] = self._contract(factors, first)
        own = range(self.split) if first else range(self.split, self.t.order)
        x = self.half[first]  # own modes' cells x rank
        for k in reversed(own):
            if k != n:
                at = list(own).index(k)
                x = np.einsum("...ar,ar->...r", np.moveaxis(x, at, -2), factors[k]) if x.ndim > 2 else x
        return x

    def _contract(self, factors: Sequence[np.ndarray], first: bool) -> np.ndarray:
        from .tensors import BlockTensor

        own = list(range(self.split) if first else range(self.split, self.t.order))
        sizes = [self.shape[k] for k in own]
        t, rank = self.t, factors[0].shape[1]
        if not isinstance(t, BlockTensor):
            t = t.to_blocks([1] * t.order)

        def product(lo: list[int], x: np.ndarray) -> np.ndarray:
            mine = [f[a : a + s] for f, a, s in zip(factors, lo, x.shape, strict=True)]
            others = [k for k in range(x.ndim) if k not in own]
            y = np.tensordot(x, mine[others[-1]], (others[-1], 0))
            for k in reversed(others[:-1]):
                y = np.einsum("...ar,ar->...r", np.moveaxis(y, k, -2), mine[k])
            out = np.zeros((*sizes, rank))
            out[tuple(slice(lo[k], lo[k] + x.shape[k]) for k in own)] = y
            # Pieces are added by the first row of mode 0; here every piece is whole, so it counts from row 0.
            return out.reshape(-1, rank)

        whole = _WholePieces(t)
        return whole.sum(int(np.prod(sizes)), rank, product).reshape(*sizes, rank)

    def norm2(self) -> float:
        return self.t.norm2()


class _WholePieces:
    """Sum of equally shaped arrays over all blocks."""

    def __init__(self, t: Tensor):
        self.t = t

    def sum(self, rows: int, width: int, product) -> np.ndarray:
        from .tensors import PIECE, _blocks, _emit, _sum_pieces

        self.t.passes.reads += 1

        def run(batches):
            total = None
            for lo, x in _blocks(batches):
                z = product(lo, x)
                total = z if total is None else total + z
            if total is not None:
                yield _emit({0: total})

        return _sum_pieces(self.t.df.mapInArrow(run, PIECE), rows, width)


class ColumnwiseSource:
    """Nonzeros only, a component at a time, as a plan of joins and sums."""

    def __init__(self, t: Tensor):
        self.t, self.shape = t, t.shape

    def mttkrp(self, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
        from .algebra import mttkrp, rows_frame

        self.t.passes.reads += 1
        rows = [rows_frame(self.t.spark, f) for f in factors]
        out = np.zeros((self.shape[n], factors[0].shape[1]))
        for r in mttkrp(self.t.df, rows, n, factors[0].shape[1], "columnwise").collect():
            out[r["i"], r["r"]] = r["v"]
        return out

    def norm2(self) -> float:
        return self.t.norm2()


class DenseSource:
    """A small tensor on the driver."""

    def __init__(self, x: np.ndarray):
        self.x, self.shape = x, x.shape

    def mttkrp(self, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
        return core_mttkrp(self.x, list(factors), n)

    def gram(self, n: int) -> np.ndarray:
        m = unfold_dense(self.x, n)
        return m @ m.T

    def norm2(self) -> float:
        return float((self.x**2).sum())


DRAWN = {"normal": gauss, "uniform": uniform, "exponential": lambda seed, axes: -np.log(uniform(seed, axes))}


def initial(shape: Sequence[int], rank: int, init, seed: int, source=None) -> list[np.ndarray]:
    """normal, uniform, exponential: by counters; svd: leading columns of a Tucker form's factors; or given factors."""
    if not isinstance(init, str):
        return [np.array(f, float) for f in init]
    out = []
    for n, s in enumerate(shape):
        if isinstance(source, TuckerSource) and isinstance(source.form.factors[n], Tall) and init in DRAWN:
            out.append(Tall.made(s, rank, lambda at, n=n: DRAWN[init](seed + 31 * n, np.ix_(at, np.arange(rank)))))
            continue
        axes = np.ix_(np.arange(s), np.arange(rank))
        if init in DRAWN:
            out.append(DRAWN[init](seed + 31 * n, axes))
        elif init == "svd":
            u = source.form.factors[n] if isinstance(source, TuckerSource) else np.linalg.eigh(source.gram(n))[1][:, ::-1][:, :rank]
            extra = gauss(seed + 31 * n, np.ix_(np.arange(s), np.arange(max(0, rank - u.shape[1]))))
            out.append(np.hstack([u[:, :rank], extra]))
        else:
            raise ValueError(f"unknown start {init!r}")
    return out


def updated(a: np.ndarray, q: np.ndarray, t: np.ndarray, update: str, constraint: Constraint = FREE, inner: int = 1, eps: float = 1e-12) -> np.ndarray:
    """One step for the rows of a factor from q = MTTKRP rows and t = Gram of the other factors; rows don't depend on each other."""
    if update == "als":
        return constraint(_solve(q, t), np.diag(t))
    if update == "mu":
        return constraint(a * np.maximum(q, 0.0) / (a @ t + eps))
    if update == "pg":
        step = max(float(np.linalg.eigvalsh(t)[-1]), eps)
        return constraint(a - (a @ t - q) / step, step)
    if update == "hals":
        a = a.copy()
        for _ in range(inner):
            for r in range(a.shape[1]):
                curvature = max(float(t[r, r]), eps)
                a[:, r] = constraint(a[:, r] + (q[:, r] - a @ t[:, r]) / curvature, curvature)
        return a
    raise ValueError(f"unknown update {update!r}; there are {UPDATES}")


def _solve(q: np.ndarray, t: np.ndarray) -> np.ndarray:
    if np.linalg.cond(t) < 1e12:
        return np.linalg.solve(t, q.T).T
    return q @ np.linalg.pinv(t)


def fit_cp(source, rank: int, update: str = "als", constraint: Constraint | dict | None = None, init="normal", seed: int = 1, max_iter: int = 1000, tol: float = 1e-6, inner: int = 1, extrapolate: bool = False) -> CPModel:
    """Sweep over the modes until the fit changes by less than tol; the fit needs no pass of its own."""
    shape, began = source.shape, time.perf_counter()
    order = len(shape)
    if update in ("mu", "hals") and constraint is None:
        constraint = nonneg()
    limits = per_mode(constraint, order)
    if update == "mu" and any(not c.clip for c in limits):
        raise ValueError("multiplicative updates only make sense for nonnegative factors")
    factors = initial(shape, rank, init, seed, getattr(source, "t", source))
    factors = [np.maximum(f, 1e-6) if c.clip and update == "mu" else c(f) for f, c in zip(factors, limits, strict=True)]
    norm2, history, before = source.norm2(), [], None
    for k in range(max_iter):
        for n in range(order):
            q = source.mttkrp(factors, n)
            t = gram_hadamard([f.T @ f for f in factors], n)
            factors[n] = updated(factors[n], q, t, update, limits[n], inner)
            if n < order - 1:  # the last factor keeps the scale
                norms = np.linalg.norm(factors[n], axis=0)
                norms[norms < 1e-300] = 1
                factors[n] = factors[n] / norms
                factors[-1] = factors[-1] * norms
        model2 = gram_hadamard([f.T @ f for f in factors]).sum()
        residual = max(0.0, norm2 - 2 * float((q * factors[-1]).sum()) + float(model2))
        history.append(1 - float(np.sqrt(residual / norm2)) if norm2 else 1.0)
        if k and abs(history[-1] - history[-2]) < tol:
            break
        if extrapolate and before is not None and all(c.free for c in limits) and k % 3 == 2:
            factors = _line_step(source, factors, before, norm2, history[-1], k + 1)
        before = list(factors)
    return CPModel(factors, None, history, {"iterations": len(history), "seconds": time.perf_counter() - began})


def _line_step(source, now: list[np.ndarray], before: list[np.ndarray], norm2: float, fit: float, k: int) -> list[np.ndarray]:
    """Go on along the last change; kept only if the fit gains by it."""
    ahead = [a + (k ** (1 / 3) - 1) * (a - b) for a, b in zip(now, before, strict=True)]
    q = source.mttkrp(ahead, len(ahead) - 1)
    residual = max(0.0, norm2 - 2 * float((q * ahead[-1]).sum()) + float(gram_hadamard([f.T @ f for f in ahead]).sum()))
    return ahead if 1 - np.sqrt(residual / norm2) > fit else now


def cp_als(t, rank: int, mttkrp: str = "auto", **options) -> CPModel:
    """Direct alternating least squares on the tensor. mttkrp: auto, reuse (two passes a sweep) or columnwise."""
    source = {"auto": lambda x: x, "reuse": ReuseSource, "columnwise": ColumnwiseSource}[mttkrp](t)
    return fit_cp(source, rank, "als", **options)


def cp_mu(t, rank: int, init="uniform", **options) -> CPModel:
    return fit_cp(t, rank, "mu", init=init, **options)


def cp_hals(t, rank: int, init="uniform", **options) -> CPModel:
    return fit_cp(t, rank, "hals", init=init, **options)


def compressed_cp(form: TuckerModel, rank: int, update: str = "als", constraint=None, how: str = "contract", init: str | list | None = None, n_starts: int = 1, seed: int = 1, **options) -> CPModel:
    """CP of the whole tensor from its Tucker form: gradients cost small products, constraints hold for the factors themselves."""
    init = init or ("normal" if update == "als" else "uniform")
    if update == "hals" and how == "contract" and not options.keys() - {"max_iter", "tol"}:
        models = [fit_hals_blocks(form, rank, constraint, init, seed + 1000 * k, **options) for k in range(n_starts)]
    else:
        models = [fit_cp(TuckerSource(form, how), rank, update, constraint, init, seed + 1000 * k, **options) for k in range(n_starts)]
    best = max(models, key=lambda m: m.history[-1])
    best.stats |= {"starts": n_starts, "passes": 0}
    return best


def fit_hals_blocks(form: TuckerModel, rank: int, constraint=None, init="uniform", seed: int = 1, max_iter: int = 1000, tol: float = 1e-6) -> CPModel:
    """fit_cp's column-wise sweeps on a Tucker form, a block of rows at a time while it is in the cache.

    Factors lie column by column and are changed in place. Of each only UtA, AtA and the scale of its columns is needed between
    updates: these small sums are made while a block is at hand.
    """
    shape, began, order = tuple(u.shape[0] for u in form.factors), time.perf_counter(), form.core.ndim
    limits = per_mode(nonneg() if constraint is None else constraint, order)
    start = [f.mapped(c) if isinstance(f, Tall) else c(f) for f, c in zip(initial(shape, rank, init, seed, TuckerSource(form)), limits, strict=True)]
    vs, grams = [u.T @ a for u, a in zip(form.factors, start, strict=True)], [a.T @ a for a in start]
    turned = [a if isinstance(a, Tall) else np.ascontiguousarray(a.T) for a in start]
    scales, norm2, history = [np.ones(rank) for _ in shape], float((form.core**2).sum()), []

    for k in range(max_iter):
        for n, size in enumerate(shape):
            h, t = core_mttkrp(form.core, vs, n), gram_hadamard(grams, n)
            curvature = np.maximum(np.diag(t), 1e-12)
            turn, mixed = np.ascontiguousarray(h.T) / curvature[:, None], t / curvature[:, None]

            def change(a: np.ndarray, u: np.ndarray) -> np.ndarray:
                q = turn @ u.T
                for r in range(rank):
                    x = q[r]
                    x -= mixed[r] @ a
                    x += a[r]
                    a[r] = limits[n](x, curvature[r])
                return a

            if isinstance(turned[n], Tall):
                turned[n] = (turned[n] * scales[n]).step(form.factors[n], lambda a, u: change(np.array(a.T, order="C"), u).T)
                vs[n], grams[n] = turned[n].met[1], turned[n].own
            else:
                vs[n], grams[n] = np.zeros_like(vs[n]), np.zeros((rank, rank))
                for lo in range(0, size, BLOCK_ROWS):
                    u = form.factors[n][lo : lo + BLOCK_ROWS]
                    a = change(turned[n][:, lo : lo + BLOCK_ROWS] * scales[n][:, None], u)
                    turned[n][:, lo : lo + BLOCK_ROWS] = a
                    vs[n] += u.T @ a.T
                    grams[n] += a @ a.T
            scales[n] = np.ones(rank)
            if n < order - 1:  # the last factor keeps the scale
                norms = np.sqrt(np.diag(grams[n]))
                norms[norms < 1e-300] = 1
                for m, by in ((n, 1 / norms), (order - 1, norms)):
                    vs[m], grams[m], scales[m] = vs[m] * by, grams[m] * np.outer(by, by), scales[m] * by
        residual = max(0.0, norm2 - 2 * float((h * vs[-1]).sum()) + float(gram_hadamard(grams).sum()))
        history.append(1 - float(np.sqrt(residual / norm2)) if norm2 else 1.0)
        if k and abs(history[-1] - history[-2]) < tol:
            break
    factors = [a * s if isinstance(a, Tall) else (a * s[:, None]).T for a, s in zip(turned, scales, strict=True)]
    return CPModel(factors, None, history, {"iterations": len(history), "seconds": time.perf_counter() - began})


def core_then_lift_cp(form: TuckerModel, rank: int, constraint=None, **options) -> CPModel:
    """CP of the core, lifted by the bases; entries of the product obey no constraint, so none is accepted."""
    if any(not c.free for c in per_mode(constraint, form.core.ndim)):
        raise ValueError("a constraint on the core's factors says nothing about the lifted ones; use compressed_cp")
    small = fit_cp(DenseSource(form.core), rank, "als", **options)
    return CPModel([u @ v for u, v in zip(form.factors, small.factors, strict=True)], None, small.history, small.stats)


def core_domain_cp(form: TuckerModel, rank: int, constraint: Constraint, seed: int = 1, max_iter: int = 200, tol: float = 1e-6) -> CPModel:
    """Minimise over the small matrices while their lifted product is pushed into the set: step, lift, project, return."""
    limits = per_mode(constraint, form.core.ndim)
    lifted = [c(f) for f, c in zip(initial([u.shape[0] for u in form.factors], rank, "uniform" if limits[0].clip else "normal", seed), limits, strict=True)]
    vs = [u.T @ a for u, a in zip(form.factors, lifted, strict=True)]
    norm2, history = float((form.core**2).sum()), []
    for k in range(max_iter):
        for n, u in enumerate(form.factors):
            h = core_mttkrp(form.core, vs, n)
            t = gram_hadamard([a.T @ a for a in lifted], n)
            lifted[n] = limits[n](u @ _solve(h, t), np.diag(t))
            vs[n] = u.T @ lifted[n]
        inner = float((core_mttkrp(form.core, vs, len(vs) - 1) * vs[-1]).sum())
        history.append(1 - float(np.sqrt(max(0.0, norm2 - 2 * inner + gram_hadamard([a.T @ a for a in lifted]).sum()) / norm2)))
        if k and abs(history[-1] - history[-2]) < tol:
            break
    return CPModel(lifted, None, history, {"iterations": len(history)})


def gradient(source, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
    """Gradient of half the squared error in one factor: A T - Q."""
    return factors[n] @ gram_hadamard([f.T @ f for f in factors], n) - source.mttkrp(factors, n)


def cp_diagnostics(model: CPModel) -> dict[str, float]:
    """Congruence of the closest pair of components (near -1 or 1: degenerate), and the spread of weights."""
    m = model.normalise()
    c = gram_hadamard([f.T @ f for f in m.factors])
    off = c - np.diag(np.diag(c))
    return {"congruence": float(off.flat[np.abs(off).argmax()]), "weight_ratio": float(m.weights.max() / max(m.weights.min(), 1e-300))}


# Factors too long for the driver --------------------------------------------------------------------------------


def compressed_rows(modes: Sequence[DataFrame], core: np.ndarray, rank: int, update: str = "als", constraint=None, max_iter: int = 50, tol: float = 1e-6) -> tuple[list[DataFrame], list[float]]:
    """compressed_cp for modes given as rows (i, u, a): basis row and factor row side by side.

    An update is a projection of each row with two small matrices, then one small sum; rows never move. Each mode's rows are
    stored after its update, so lineage stays short.
    """
    from ..sources.storage import stored

    if update in ("mu", "hals") and constraint is None:
        constraint = nonneg()
    limits, modes = per_mode(constraint, len(modes)), list(modes)
    small = [_pair(m) for m in modes]
    norm2, history = float((core**2).sum()), []
    for k in range(max_iter):
        for n, rows in enumerate(modes):
            h = core_mttkrp(core, [v for v, _ in small], n)
            t = gram_hadamard([g for _, g in small], n)
            modes[n] = stored(_step(rows, h, t, update, limits[n]))
            small[n] = _pair(modes[n])
        inner = float((h * small[-1][0]).sum())
        history.append(1 - float(np.sqrt(max(0.0, norm2 - 2 * inner + gram_hadamard([g for _, g in small]).sum()) / norm2)))
        if k and abs(history[-1] - history[-2]) < tol:
            break
    return modes, history


def _matrices(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    return tuple(np.stack([np.asarray(x, float) for x in batch.column(c).to_pylist()]) for c in ("u", "a"))


def _pair(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """UtA and AtA of rows (i, u, a)."""

    def run(batches):
        total = None
        for batch in batches:
            if batch.num_rows:
                u, a = _matrices(batch)
                m = np.vstack([u.T @ a, a.T @ a])
                total = m if total is None else total + m
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.shape[1]], pa.int32()), pa.array([total.tobytes()], pa.binary())], ["k", "m"])

    total = sum(np.frombuffer(r["m"]).reshape(-1, r["k"]) for r in rows.mapInArrow(run, "k int, m binary").collect())
    return total[: -total.shape[1]], total[-total.shape[1] :]


def _step(rows: DataFrame, h: np.ndarray, t: np.ndarray, update: str, limit: Constraint) -> DataFrame:
    def run(batches):
        for batch in batches:
            if batch.num_rows:
                u, a = _matrices(batch)
                a = updated(a, u @ h, t, update, limit)
                yield batch.set_column(batch.schema.get_field_index("a"), "a", pa.array(list(a), pa.list_(pa.float64())))

    return rows.mapInArrow(run, rows.schema)


def component_frame(spark: SparkSession, model: CPModel) -> DataFrame:
    """mode, i, r, v and the component's weight."""
    m = model if model.weights is not None else model.normalise()
    rows = [(n, i, r, float(x), float(m.weights[r])) for n, f in enumerate(m.factors) for i, row in enumerate(f) for r, x in enumerate(row)]
    return spark.createDataFrame(rows, "mode int, i long, r int, v double, weight double")
