"""Related CP methods that the compressed one is compared with: replicas, partitions, samples."""

from __future__ import annotations

from collections.abc import Sequence
from math import ceil, prod

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..functions.counter import gauss, uniform
from .algebra import multiply_all
from .cluster import assignment
from .cp import CPModel, DenseSource, fit_cp
from .tensors import BlockTensor, CooTensor, Tensor, _blocks, _emit, _sum_pieces, PIECE


def replica_count(shape: Sequence[int], small: int, anchors: int) -> int:
    """Replicas needed: the stacked compressions must determine the longest mode."""
    return max(ceil((max(shape) - anchors) / max(1, small - anchors)), 2)


def anchored_replica_cp(t: BlockTensor, rank: int, small: int | None = None, anchors: int | None = None, replicas: int | None = None, seed: int = 1, max_iter: int = 300, refine: int = 0) -> CPModel:
    """Compress the tensor by many random matrices that share their first columns, decompose each small tensor by itself,
    match components by the shared part, and solve for the factors from the stacked compressions.

    All replicas are compressed in one pass over the data; their decompositions are independent tasks.
    """
    anchors = anchors or rank + 2
    small = small or max(2 * rank, anchors + 4)
    replicas = replicas or replica_count(t.shape, small, anchors) + 1
    if replicas * (small - anchors) + anchors < max(t.shape):
        raise ValueError(f"{replicas} replicas of {small} rows can't determine {max(t.shape)}")
    order = t.order
    mats = [[np.hstack([gauss(seed + n, np.ix_(np.arange(s), np.arange(anchors))), gauss(seed + 100 * (p + 1) + n, np.ix_(np.arange(s), np.arange(small - anchors)))]) / np.sqrt(s) for n, s in enumerate(t.shape)] for p in range(replicas)]
    t.passes.reads += 1

    def compress(batches):
        total = None
        for lo, x in _blocks(batches):
            z = np.stack([multiply_all(x, [m[a : a + s].T for m, a, s in zip(ms, lo, x.shape, strict=True)]).ravel() for ms in mats])
            total = z if total is None else total + z
        if total is not None:
            yield _emit({0: total})

    cores = _sum_pieces(t.df.mapInArrow(compress, PIECE), replicas, small**order)
    rows = t.spark.createDataFrame([(p, c.tobytes()) for p, c in enumerate(cores)], "p int, data binary")

    def decompose(group: pd.DataFrame) -> pd.DataFrame:
        x = np.frombuffer(group["data"].iloc[0]).reshape([small] * order)
        best = max((fit_cp(DenseSource(x), rank, "als", seed=seed + 13 * k, max_iter=max_iter, tol=1e-9) for k in range(3)), key=lambda m: m.history[-1])
        return pd.DataFrame({"p": group["p"].iloc[:1], "data": [np.stack([f for f in best.factors]).tobytes()]})

    parts = {r["p"]: np.frombuffer(r["data"]).reshape(order, small, rank) for r in rows.groupBy("p").applyInPandas(decompose, "p int, data binary").collect()}
    factors = _stitch(parts, mats, anchors, rank)
    model = CPModel(factors, None, [], {"replicas": replicas, "n_cp": replicas, "passes": 1})
    return _scaled(t, model)


def _stitch(parts: dict[int, np.ndarray], mats, anchors: int, rank: int) -> list[np.ndarray]:
    order, first = parts[0].shape[0], None
    stacked: list[list[np.ndarray]] = [[] for _ in range(order)]
    for p in sorted(parts):
        fs = [f.copy() for f in parts[p]]
        for f in fs:  # scale and sign by the shared rows
            top = f[:anchors]
            f /= np.where(np.abs(top[np.abs(top).argmax(0), np.arange(rank)]) > 1e-12, np.linalg.norm(top, axis=0) * np.sign(top[np.abs(top).argmax(0), np.arange(rank)]), 1.0)
        if first is None:
            first = fs
        else:
            similarity = prod_abs([a[:anchors].T @ f[:anchors] for a, f in zip(first, fs, strict=True)])
            by = assignment(-similarity)
            fs = [f[:, by] for f in fs]
            for k, f in enumerate(fs):
                f *= np.sign((first[k][:anchors] * f[:anchors]).sum(0))
        for k, f in enumerate(fs):
            stacked[k].append(f)
    out = []
    for n in range(order):
        m = np.vstack([mats[p][n].T for p in sorted(parts)])
        out.append(np.linalg.lstsq(m, np.vstack(stacked[n]), rcond=None)[0])
    return out


def prod_abs(ms: Sequence[np.ndarray]) -> np.ndarray:
    out = np.abs(ms[0])
    for m in ms[1:]:
        out = out * np.abs(m)
    return out


def _scaled(t: Tensor, model: CPModel) -> CPModel:
    """Component weights by least squares on the whole tensor: one pass."""
    fs = [f / np.maximum(np.linalg.norm(f, axis=0), 1e-300) for f in model.factors]
    q = t.mttkrp(fs, t.order - 1)
    g = np.multiply.reduce([f.T @ f for f in fs])
    weights = np.linalg.lstsq(g, (q * fs[-1]).sum(0), rcond=None)[0]
    fs[-1] = fs[-1] * weights
    residual = t.norm2() - 2 * float((q / 1 * fs[-1]).sum()) + float(np.multiply.reduce([f.T @ f for f in fs]).sum())
    norm2 = t.norm2()
    return CPModel(fs, None, [1 - float(np.sqrt(max(0.0, residual) / norm2))], model.stats)


def partition_merge_cp(t: BlockTensor, rank: int, sub_rank: int | None = None, seed: int = 1, max_iter: int = 400) -> CPModel:
    """A CP for each block, in its own task; the global factors then see the data only through these small models."""
    sub_rank = sub_rank or rank
    t.passes.reads += 1

    def decompose(group: pd.DataFrame) -> pd.DataFrame:
        out = []
        for lo, dims, data in zip(group["lo"], group["dims"], group["data"], strict=True):
            x = np.frombuffer(data).reshape([int(d) for d in dims])
            m = max((fit_cp(DenseSource(x), min(sub_rank, prod(x.shape)), "als", seed=seed + k, max_iter=max_iter, tol=1e-11) for k in range(4)), key=lambda m: m.history[-1])
            out.append({"lo": lo, "dims": dims, "data": np.vstack(m.factors).tobytes()})
        return pd.DataFrame(out)

    found = t.df.groupBy(F.col("lo").cast("string").alias("_at")).applyInPandas(decompose, "lo array<long>, dims array<long>, data binary").collect()
    parts = []
    for r in found:
        m = np.frombuffer(r["data"]).reshape(sum(r["dims"]), -1)
        parts.append((r["lo"], r["dims"], np.split(m, np.cumsum(r["dims"])[:-1])))

    class Parts:
        shape = t.shape

        def mttkrp(self, factors, n):
            out = np.zeros((t.shape[n], factors[0].shape[1]))
            for lo, dims, fs in parts:
                weights = np.multiply.reduce([f.T @ a[b : b + d] for k, (f, a, b, d) in enumerate(zip(fs, factors, lo, dims, strict=True)) if k != n])
                out[lo[n] : lo[n] + dims[n]] += fs[n] @ weights
            return out

        def norm2(self):
            return sum(float(np.multiply.reduce([f.T @ f for f in fs]).sum()) for _, _, fs in parts)

    best = max((fit_cp(Parts(), rank, "als", seed=seed + 50 + k, max_iter=5 * max_iter, tol=1e-12) for k in range(4)), key=lambda m: m.history[-1])
    best.stats |= {"n_cp": len(parts), "passes": 1}
    return best


def sampled_cp(t: CooTensor | BlockTensor, rank: int, fraction: float = 0.5, repeats: int = 4, shared: float = 0.5, seed: int = 1, max_iter: int = 300) -> CPModel:
    """CP of sub-tensors on sampled indices (drawn by marginal energy, some shared by all), merged by the shared ones."""
    order = t.order
    cells = t.df if isinstance(t, CooTensor) else t.to_cells().df
    keep = []
    for n, s in enumerate(t.shape):
        energy = np.zeros(s)
        for r in cells.groupBy(f"i{n + 1}").agg(F.sum(F.col("v") * F.col("v")).alias("w")).collect():
            energy[r[0]] = r["w"]
        take, common = max(rank + 1, round(fraction * s)), max(rank, round(fraction * shared * s))
        first = np.argsort(np.log(uniform(seed + n, [np.arange(s)])) / np.maximum(energy, 1e-12))[::-1][:common]
        sets = []
        for p in range(repeats):
            rest = np.setdiff1d(np.arange(s), first)
            # Indices that no earlier sample took come first, so all are covered.
            covered = set(np.concatenate(sets).tolist()) if sets else set()
            score = uniform(seed + 100 * p + n, [rest]) + np.array([i not in covered for i in rest.tolist()], float)
            sets.append(np.concatenate([first, rest[np.argsort(-score)][: max(take - common, ceil(len(rest) / repeats))]]))
        keep.append((common, sets))
    t.passes.reads += 1
    merged = [np.zeros((s, rank)) for s in t.shape]
    count = [np.zeros(s) for s in t.shape]
    reference = None
    for p in range(repeats):
        chosen = [sets[p] for _, sets in keep]
        part = cells
        for n, ids in enumerate(chosen):
            part = part.join(F.broadcast(t.spark.createDataFrame([(int(i), k) for k, i in enumerate(ids)], f"i{n + 1} long, j{n + 1} long")), f"i{n + 1}")
        x = np.zeros([len(c) for c in chosen])
        for r in part.select(*[f"j{n + 1}" for n in range(order)], "v").collect():
            x[tuple(r[:order])] = r["v"]
        model = max((fit_cp(DenseSource(x), rank, "als", seed=seed + 7 * p + k, max_iter=max_iter, tol=1e-10) for k in range(3)), key=lambda m: m.history[-1])
        fs = model.absorbed()
        tops = [f[: keep[n][0]] for n, f in enumerate(fs)]
        if reference is None:
            reference = tops
        else:
            unit = [(a / np.linalg.norm(a, axis=0)).T @ (b / np.linalg.norm(b, axis=0)) for a, b in zip(reference, tops, strict=True)]
            by = assignment(-prod_abs(unit))
            fs = [f[:, by] for f in fs]
            for n, f in enumerate(fs):
                top = f[: keep[n][0]]
                f *= (reference[n] * top).sum(0) / np.maximum((top * top).sum(0), 1e-300)
        for n, (f, ids) in enumerate(zip(fs, chosen, strict=True)):
            merged[n][ids] += f
            count[n][ids] += 1
    fs = [m / np.maximum(c, 1)[:, None] for m, c in zip(merged, count, strict=True)]
    return _scaled(t, CPModel(fs, None, [], {"n_cp": repeats, "passes": 1}))
