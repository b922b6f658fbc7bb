"""Nonnegative Tucker decomposition, of the tensor or of its compact form (then without a pass over the data)."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

from ..functions.counter import uniform
from .algebra import multiply_all, unfold_dense
from .constraints import nonneg
from .cp import updated
from .tall import Tall, norms
from .tensors import Tensor
from .tucker import TuckerModel


class _Source:
    def tall(self, n: int) -> bool:
        return False


class _Compact(_Source):
    """Products that the updates need, from core and bases."""

    def __init__(self, form: TuckerModel):
        self.form, self.shape = form, tuple(u.shape[0] for u in form.factors)
        self.norm2 = float((form.core**2).sum())

    def tall(self, n: int) -> bool:
        return isinstance(self.form.factors[n], Tall)

    def projected(self, fs: Sequence[np.ndarray], n: int) -> np.ndarray:
        """Unfolding n after products with all other factors' transposes."""
        return self.form.factors[n] @ self.coordinates(fs, n)

    def coordinates(self, fs: Sequence[np.ndarray], n: int) -> np.ndarray:
        """The same in the coordinates of basis n: small, however long the mode is."""
        small = [f.T @ u for f, u in zip(fs, self.form.factors, strict=True)]
        return unfold_dense(multiply_all(self.form.core, small, skip=n), n)


class _Direct(_Source):
    def __init__(self, t: Tensor):
        self.t, self.shape, self.norm2 = t, t.shape, t.norm2()

    def projected(self, fs: Sequence[np.ndarray], n: int) -> np.ndarray:
        return self.t.project(n, fs)


class _Dense(_Source):
    """A small tensor on the driver."""

    def __init__(self, x: np.ndarray):
        self.x, self.shape, self.norm2 = x, x.shape, float((x**2).sum())

    def projected(self, fs: Sequence[np.ndarray], n: int) -> np.ndarray:
        return unfold_dense(multiply_all(self.x, fs, skip=n, transpose=True), n)


def _fit(source, ranks: Sequence[int], update: str, max_iter: int, tol: float, seed: int, core_steps: int = 5) -> TuckerModel:
    order = len(ranks)
    fs = [uniform(seed + 17 * n, np.ix_(np.arange(s), np.arange(r))) for n, (s, r) in enumerate(zip(source.shape, ranks, strict=True)) if not source.tall(n)]
    for n in filter(source.tall, range(order)):
        fs.insert(n, Tall.made(source.shape[n], ranks[n], lambda at, n=n: uniform(seed + 17 * n, np.ix_(at, np.arange(ranks[n])))))
    core = uniform(seed + 997, np.ix_(*[np.arange(r) for r in ranks]))
    history = []
    for k in range(max_iter):
        for n in range(order):
            compact = isinstance(source, _Compact)  # then the mode's rows are met by the small product only
            x = source.coordinates(fs, n) if compact else source.projected(fs, n)
            c = unfold_dense(core, n)
            grams = [f.T @ f for f in fs]
            t = c @ unfold_dense(multiply_all(core, grams, skip=n), n).T
            if source.tall(n):
                small = x @ c.T
                fs[n] = fs[n].step(source.form.factors[n], lambda a, u: updated(a, u @ small, t, update, nonneg(1e-16)))
            else:
                fs[n] = updated(fs[n], source.form.factors[n] @ (x @ c.T) if compact else x @ c.T, t, update, nonneg(1e-16))
            if n < order:
                sizes = np.maximum(norms(fs[n]), 1e-12)
                fs[n] = fs[n] / sizes
                core = np.moveaxis(np.moveaxis(core, n, -1) * sizes, -1, n)
        # The last projection, with the newest last factor, is the core's data term.
        last = fs[-1].T @ source.form.factors[-1] @ x if compact else fs[-1].T @ x
        data = np.moveaxis(last.reshape([ranks[-1], *ranks[:-1]], order="F"), 0, order - 1)
        grams = [f.T @ f for f in fs]
        top = float(np.prod([np.linalg.eigvalsh(g)[-1] for g in grams]))
        for _ in range(core_steps):
            now = multiply_all(core, grams)
            if update == "mu":
                core = core * np.maximum(data, 0) / (now + 1e-12)
            else:
                core = np.maximum(core - (now - data) / top, 0)
        residual = source.norm2 - 2 * (core * data).sum() + (core * multiply_all(core, grams)).sum()
        history.append(1 - float(np.sqrt(max(0.0, residual) / source.norm2)))
        if k and abs(history[-1] - history[-2]) < tol:
            break
    return TuckerModel(core, fs, source.norm2, {"history": history, "iterations": len(history)})


def compressed_ntd(form: TuckerModel, ranks: Sequence[int], update: str = "hals", max_iter: int = 200, tol: float = 1e-6, seed: int = 1) -> TuckerModel:
    return _fit(_Compact(form), ranks, update, max_iter, tol, seed)


def ntd(t: Tensor | np.ndarray, ranks: Sequence[int], update: str = "hals", max_iter: int = 50, tol: float = 1e-5, seed: int = 1) -> TuckerModel:
    """The direct twin: a pass over the data (or over an array on the driver) for every mode of every sweep."""
    return _fit(_Dense(t) if isinstance(t, np.ndarray) else _Direct(t), ranks, update, max_iter, tol, seed)
