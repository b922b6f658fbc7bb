"""Distributed tensors, as cells or as dense blocks, with the four sums that all methods are made of.

Both layouts answer the same calls: `sketch`, `project`, `mttkrp` and `gram` give a matrix of one mode, `shrink` a smaller
tensor. Each is a numpy kernel over Arrow batches that adds up what its partition has before anything is exchanged, then a
sum by row chunk. Random test matrices are regenerated from global coordinates inside the kernel, so neither the grid nor the
number of partitions can change a result beyond rounding.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field
from functools import reduce
from math import ceil, prod

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.counter import draw, gauss
from .algebra import kronecker, multiply, multiply_all, unfold_dense
from .orth import polish_map
from .tall import Columns, Drawn, Tall

#: Rows of a mode that travel as one piece, and numbers that a result on the driver may have.
CHUNK, DRIVER_NUMBERS = 4096, 20_000_000
#: Partitions whose pieces of a chunk are added in one task.
FAN_IN = 64
PIECE = "lo long, data binary"


@dataclass
class Passes:
    """How often the tensor has been read, how many numbers a reading left on the driver, and random bytes not sent."""

    reads: int = 0
    gathered: int = 0
    regenerated_bytes: int = 0
    broadcast_bytes: int = 0


def _sum_pieces(pieces: DataFrame, rows: int, width: int) -> np.ndarray:
    """Sum pieces of a rows x width matrix by chunk, and gather the sums."""
    if rows * width > DRIVER_NUMBERS:
        raise ValueError(f"{rows} x {width} numbers don't belong on the driver; use the row-wise methods (orth_rows, compressed_rows)")

    def add(group: pd.DataFrame) -> pd.DataFrame:
        total = np.frombuffer(group["data"].iloc[0]).copy()
        for data in group["data"].iloc[1:]:
            total += np.frombuffer(data)
        return pd.DataFrame({"lo": group["lo"].iloc[:1], "data": [total.tobytes()]})

    # Pieces of one chunk are first added in groups of FAN_IN partitions, so no task holds the pieces of all partitions.
    out = np.zeros((rows, width))
    parts = pieces.withColumn("_part", F.floor(F.spark_partition_id() / FAN_IN))
    for r in parts.groupBy("lo", "_part").applyInPandas(add, PIECE).groupBy("lo").applyInPandas(add, PIECE).collect():
        part = np.frombuffer(r["data"]).reshape(-1, width)
        out[r["lo"] : r["lo"] + len(part)] += part
    return out


def _emit(total: dict[int, np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(total), pa.int64()), pa.array([x.tobytes() for x in total.values()], pa.binary())], ["lo", "data"])


class Tensor:
    """What methods ask of a tensor."""

    df: DataFrame
    shape: tuple[int, ...]
    passes: Passes
    tall = None

    @property
    def order(self) -> int:
        return len(self.shape)

    @property
    def spark(self) -> SparkSession:
        return self.df.sparkSession


@dataclass
class CooTensor(Tensor):
    """Cells i1..iN, v; absent cells are zeros."""

    df: DataFrame
    shape: tuple[int, ...]
    passes: Passes = field(default_factory=Passes)

    def _rows(self, n: int, width: int, product: Callable[[list[np.ndarray], np.ndarray], np.ndarray]) -> np.ndarray:
        """Sum over cells of a row of numbers each, by index n. product(coords, v) -> cells x width."""
        self.passes.reads += 1
        self.passes.gathered += self.shape[n] * width
        order, rows = self.order, self.shape[n]
        step = max(1, 4_000_000 // max(1, width))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, np.ndarray] = {}
            for batch in batches:
                coords = [batch.column(k).to_numpy() for k in range(order)]
                values = batch.column(order).to_numpy()
                for a in range(0, len(values), step):
                    part = [c[a : a + step] for c in coords]
                    z = product(part, values[a : a + step])
                    by = np.argsort(part[n], kind="stable")
                    own = part[n][by]
                    starts = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]])) if len(own) else []
                    if not len(starts):
                        continue
                    sums = np.add.reduceat(z[by], starts, axis=0)
                    at = own[starts]
                    for chunk in np.unique(at // CHUNK):
                        lo = int(chunk) * CHUNK
                        inside = at // CHUNK == chunk
                        if lo not in total:
                            total[lo] = np.zeros((min(CHUNK, rows - lo), width))
                        total[lo][at[inside] - lo] += sums[inside]
            yield _emit(total)

        cells = self.df.select(*[F.col(f"i{k + 1}").cast("long") for k in range(order)], F.col("v").cast("double"))
        return _sum_pieces(cells.mapInArrow(run, PIECE), rows, width)

    def sketch(self, n: int, rank: int, seed: int, dist: str = "gaussian") -> np.ndarray:
        self.passes.regenerated_bytes += 8 * rank * prod(s for k, s in enumerate(self.shape) if k != n)

        def product(coords: list[np.ndarray], v: np.ndarray) -> np.ndarray:
            others = [c[:, None] for k, c in enumerate(coords) if k != n]
            return v[:, None] * draw(dist, seed, [*others, np.arange(rank)[None]])

        return self._rows(n, rank, product)

    def project(self, n: int, factors: Sequence[np.ndarray], right: np.ndarray | None = None) -> np.ndarray:
        """Unfolding n of the tensor times all other factors' transposes (times `right`, if given)."""
        others = [(k, f) for k, f in enumerate(factors) if k != n]
        inner = prod(f.shape[1] for _, f in others)

        def product(coords: list[np.ndarray], v: np.ndarray) -> np.ndarray:
            z = v[:, None]
            for k, f in others:
                z = (f[coords[k]][:, :, None] * z[:, None, :]).reshape(len(v), -1)
            return z if right is None else z @ right

        return self._rows(n, inner if right is None else right.shape[1], product)

    def mttkrp(self, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
        def product(coords: list[np.ndarray], v: np.ndarray) -> np.ndarray:
            z = np.repeat(v[:, None], factors[0].shape[1], 1)
            for k, f in enumerate(factors):
                if k != n:
                    z *= f[coords[k]]
            return z

        return self._rows(n, factors[0].shape[1], product)

    def shrink(self, n: int, u: np.ndarray) -> CooTensor:
        """Mode-n product with the transpose of u: a join and one sum for each component."""
        from .algebra import rows_frame, ttm

        self.passes.reads += 1
        cells = ttm(self.df, rows_frame(self.spark, u), n, u.shape[1])
        return CooTensor(cells, tuple(u.shape[1] if k == n else s for k, s in enumerate(self.shape)), self.passes)

    def gram(self, n: int) -> np.ndarray:
        """Unfolding n times its transpose: cells that share the other coordinates meet in a join."""
        rows = self.shape[n]
        if rows * rows > DRIVER_NUMBERS:
            raise ValueError(f"a Gram of {rows} rows belongs to the sketched methods")
        self.passes.reads += 1
        others = [f"i{k + 1}" for k in range(self.order) if k != n]
        other = self.df.select(*others, F.col(f"i{n + 1}").alias("j"), F.col("v").alias("w"))
        out = np.zeros((rows, rows))
        for r in self.df.join(other, others).groupBy(F.col(f"i{n + 1}").alias("i"), "j").agg(F.sum(F.col("v") * F.col("w")).alias("v")).collect():
            out[r["i"], r["j"]] = r["v"]
        return out

    def norm2(self) -> float:
        self.passes.reads += 1
        return float(self.df.agg(F.sum(F.col("v") * F.col("v"))).first()[0] or 0)

    def dense(self) -> np.ndarray:
        if prod(self.shape) > DRIVER_NUMBERS:
            raise ValueError("too many cells for the driver")
        out = np.zeros(self.shape)
        for r in self.df.collect():
            out[tuple(r[k] for k in range(self.order))] += r[self.order]
        return out

    def kept(self) -> CooTensor:
        """The same cells, stored, so that repeated passes don't repeat what made them."""
        from ..sources.storage import stored

        return CooTensor(stored(self.df), self.shape, self.passes)

    def to_blocks(self, grid: Sequence[int]) -> BlockTensor:
        """Dense blocks over a grid: one exchange by block, then each block is filled in its task."""
        cuts = [cut_points(s, g) for s, g in zip(self.shape, grid, strict=True)]
        order = self.order
        block = None
        for k, c in enumerate(cuts):
            own = sum((F.when(F.col(f"i{k + 1}") >= int(x), 1).otherwise(0) for x in c[1:-1]), F.lit(0))
            block = own if block is None else block * int(grid[k]) + own

        def fill(group: pd.DataFrame) -> pd.DataFrame:
            b, s = int(group["_b"].iloc[0]), []
            for g in reversed(grid):
                s.append(b % g)
                b //= g
            s = s[::-1]
            lo = [int(cuts[k][s[k]]) for k in range(order)]
            dims = [int(cuts[k][s[k] + 1]) - lo[k] for k in range(order)]
            data = np.zeros(dims)
            np.add.at(data, tuple(group[f"i{k + 1}"].to_numpy() - lo[k] for k in range(order)), group["v"].to_numpy())
            return pd.DataFrame({"lo": [lo], "dims": [dims], "data": [data.tobytes()]})

        blocks = self.df.withColumn("_b", block).groupBy("_b").applyInPandas(fill, BLOCK)
        return BlockTensor(blocks, self.shape, self.passes)


BLOCK = "lo array<long>, dims array<long>, data binary"


def cut_points(size: int, parts: int) -> list[int]:
    """Starts of nearly equal parts, and the end."""
    return [round(k * size / parts) for k in range(parts + 1)]


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list[int], np.ndarray]]:
    for batch in batches:
        for i in range(batch.num_rows):
            dims = batch.column(1)[i].as_py()
            yield batch.column(0)[i].as_py(), np.frombuffer(batch.column(2)[i].as_buffer()).reshape(dims)


def _own(sent: Sequence, lo: list[int], x: np.ndarray) -> list[np.ndarray | None]:
    """Rows of the factors that belong to a block."""
    return [None if f is None else f.part(a, x, k) if isinstance(f, (Columns, Drawn)) else f[a : a + x.shape[k]] for k, (f, a) in enumerate(zip(sent, lo, strict=True))]


@dataclass
class BlockTensor(Tensor):
    """Dense sub-tensors over a grid: lo (first index of each mode), dims, data (row-major doubles).

    Blocks with the same place may be partial sums (after a lazy shrink): a finished mode starts at 0 in all of them, so random
    numbers don't tell the partial blocks apart, and as every call is linear the sums come out the same.

    tall: a mode along which alone the blocks are cut, each place once; matrices of its rows are `Tall`.
    """

    df: DataFrame
    shape: tuple[int, ...]
    passes: Passes = field(default_factory=Passes)
    tall: int | None = None

    def _pieces(self, n: int, width: int, product: Callable[[list[int], np.ndarray], np.ndarray], columns: Callable[[], np.ndarray] | None = None) -> np.ndarray | Tall:
        """Sum over blocks of product(lo, block) -> rows of mode n x width, by the rows' first index. columns: the small matrix that
        makes them from the unfolding, if there is one."""
        self.passes.reads += 1
        self.passes.gathered += self.shape[n] * width
        apart = n == self.tall

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, np.ndarray] = {}
            for lo, x in _blocks(batches):
                z = product(lo, x)
                if apart:
                    yield _emit({lo[n]: z})
                else:
                    total[lo[n]] = total[lo[n]] + z if lo[n] in total else z
            yield _emit(total)

        if apart:
            from ..sources.storage import stored

            return Tall.gathered(stored(self.df.mapInArrow(run, PIECE)), self.shape[n], width, columns() if columns else None, self.shape)
        return _sum_pieces(self.df.mapInArrow(run, PIECE), self.shape[n], width)

    def sketch(self, n: int, rank: int, seed: int, dist: str = "gaussian", omega: np.ndarray | None = None) -> np.ndarray:
        """omega: a broadcast test matrix instead of the regenerated one, to compare what is sent."""
        full = prod(s for k, s in enumerate(self.shape) if k != n)
        if omega is None:
            self.passes.regenerated_bytes += 8 * rank * full
        else:
            self.passes.broadcast_bytes += omega.nbytes
        shape, drawn = self.shape, []

        def product(lo: list[int], x: np.ndarray) -> np.ndarray:
            dims = [s for k, s in enumerate(x.shape) if k != n]
            grids = np.meshgrid(*[np.arange(a, a + s) for k, (a, s) in enumerate(zip(lo, x.shape, strict=True)) if k != n], indexing="ij")
            coords = [g.reshape(-1, order="F") for g in grids]
            if omega is not None:
                weights = np.cumprod([1, *[s for k, s in enumerate(shape) if k != n][:-1]])
                return unfold_dense(x, n) @ omega[sum(c * w for c, w in zip(coords, weights, strict=True))]
            out, m, step = np.zeros((x.shape[n], rank)), unfold_dense(x, n), max(1, 1_000_000 // rank)
            if prod(dims) <= step:  # blocks of the same place in the other modes meet the same numbers
                at = (dims, [a for k, a in enumerate(lo) if k != n])
                if drawn[:1] != [at]:
                    drawn[:] = [at, draw(dist, seed, [*[c[:, None] for c in coords], np.arange(rank)[None]])]
                return m @ drawn[1]
            for a in range(0, prod(dims), step):
                out += m[:, a : a + step] @ draw(dist, seed, [*[c[a : a + step, None] for c in coords], np.arange(rank)[None]])
            return out

        def columns() -> np.ndarray:
            if omega is not None:
                return omega
            coords = np.unravel_index(np.arange(full), [s for k, s in enumerate(shape) if k != n], order="F")
            return draw(dist, seed, [*[c[:, None] for c in coords], np.arange(rank)[None]])

        return self._pieces(n, rank, product, columns)

    def project(self, n: int, factors: Sequence[np.ndarray], right: np.ndarray | None = None) -> np.ndarray:
        inner = prod(f.shape[1] for k, f in enumerate(factors) if k != n)
        sent = self._sent(factors, n)

        def product(lo: list[int], x: np.ndarray) -> np.ndarray:
            # The columns follow the cells layout: later modes outermost.
            z = unfold_dense(multiply_all(x, _own(sent, lo, x), skip=n, transpose=True), n)
            return z if right is None else z @ right

        def columns() -> np.ndarray:
            return kronecker(sent, n) if right is None else kronecker(sent, n) @ right

        return self._pieces(n, inner if right is None else right.shape[1], product, columns)

    def _sent(self, factors: Sequence[np.ndarray | Tall | Drawn | None], n: int | None) -> list:
        """Factors as a kernel gets them: that of mode n not at all, a tall one as what makes its rows."""
        return [None if k == n else f.sent(self.shape) if isinstance(f, Tall) else f for k, f in enumerate(factors)]

    def mttkrp(self, factors: Sequence[np.ndarray], n: int) -> np.ndarray:
        from .algebra import core_mttkrp

        rank, sent = factors[0].shape[1], self._sent(factors, n)

        def product(lo: list[int], x: np.ndarray) -> np.ndarray:
            return core_mttkrp(x, _own(sent, lo, x), n)

        return self._pieces(n, rank, product)

    def shrink(self, n: int, u: np.ndarray, reduce: str = "eager") -> BlockTensor:
        """Mode-n product with the transpose of u. eager: partial blocks are summed now; lazy: they stay apart."""
        self.passes.reads += 1
        rank, sent = u.shape[1], self._sent([u if k == n else None for k in range(self.order)], None)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[tuple, np.ndarray] = {}
            rows = []
            for lo, x in _blocks(batches):
                y = multiply(x, _own(sent, lo, x)[n].T, n)
                lo = [0 if k == n else a for k, a in enumerate(lo)]
                if reduce == "lazy":
                    rows.append((lo, y))
                else:
                    total[tuple(lo)] = total[tuple(lo)] + y if tuple(lo) in total else y
            rows += [(list(k), y) for k, y in total.items()]
            yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in rows], pa.list_(pa.int64())), pa.array([list(y.shape) for _, y in rows], pa.list_(pa.int64())), pa.array([np.ascontiguousarray(y).tobytes() for _, y in rows], pa.binary())], ["lo", "dims", "data"])

        def add(group: pd.DataFrame) -> pd.DataFrame:
            total = np.frombuffer(group["data"].iloc[0]).copy()
            for data in group["data"].iloc[1:]:
                total += np.frombuffer(data)
            return pd.DataFrame({"lo": group["lo"].iloc[:1], "dims": group["dims"].iloc[:1], "data": [total.tobytes()]})

        blocks = self.df.mapInArrow(run, BLOCK)
        if reduce != "lazy":
            blocks = blocks.groupBy(F.col("lo").cast("string").alias("_at")).applyInPandas(add, BLOCK)
        return BlockTensor(blocks, tuple(rank if k == n else s for k, s in enumerate(self.shape)), self.passes, None if n == self.tall else self.tall)

    def _apart(self, modes: Sequence[int]) -> bool:
        """Whether each block is whole in these modes, and no two are parts of a sum."""
        whole = reduce(lambda a, b: a & b, [F.col("dims")[k] == self.shape[k] for k in modes])
        r = self.df.agg(F.min(whole), F.count("*"), F.count_distinct(F.col("lo").cast("string"))).first()
        return bool(r[0]) and r[1] == r[2]

    def gram(self, n: int) -> np.ndarray:
        """Unfolding n times its transpose: blocks that differ only in mode n meet in one task, where there are such."""
        rows, others = self.shape[n], [k for k in range(self.order) if k != n]
        if rows * rows <= DRIVER_NUMBERS and self._apart([n]):
            return self._whole_pieces(rows, lambda lo, x: unfold_dense(x, n) @ unfold_dense(x, n).T)
        self.passes.reads += 1

        def product(group: pd.DataFrame) -> pd.DataFrame:
            parts: dict[int, np.ndarray] = {}
            for lo, dims, data in zip(group["lo"], group["dims"], group["data"], strict=True):
                m = unfold_dense(np.frombuffer(data).reshape([int(d) for d in dims]), n)
                parts[int(lo[n])] = parts[int(lo[n])] + m if int(lo[n]) in parts else m
            m = np.zeros((rows, next(iter(parts.values())).shape[1]))
            for lo, part in parts.items():
                m[lo : lo + len(part)] = part
            return pd.DataFrame({"lo": [0], "data": [(m @ m.T).tobytes()]})

        key = F.concat_ws(",", *[F.col("lo")[k].cast("string") for k in others])
        return _sum_pieces(self.df.groupBy(key.alias("_at")).applyInPandas(product, PIECE), rows, rows)

    def _whole_pieces(self, rows: int, product: Callable[[list[int], np.ndarray], np.ndarray]) -> np.ndarray:
        """Sum over blocks of equally large square matrices."""
        self.passes.reads += 1

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((rows, rows))
            for lo, x in _blocks(batches):
                total += product(lo, x)
            yield _emit({0: total})

        return _sum_pieces(self.df.mapInArrow(run, PIECE), rows, rows)

    def leading(self, n: int, rank: int, factors: Sequence[np.ndarray] | None = None) -> np.ndarray | None:
        """Leading left singular vectors of unfolding n (after products with the other factors' transposes), for a mode whose Gram
        or projection doesn't belong on the driver: by the Gram of the columns, then one more pass. None if blocks aren't whole
        in the other modes, or the columns are too many too."""
        factors = factors or [np.eye(1) if k == n else np.eye(s) for k, s in enumerate(self.shape)]
        others = [k for k in range(self.order) if k != n]
        width = prod(factors[k].shape[1] for k in others)
        if width * width > DRIVER_NUMBERS or not (n == self.tall or self._apart(others)):
            return None
        sent = self._sent(factors, n)

        def product(lo: list[int], x: np.ndarray) -> np.ndarray:
            z = unfold_dense(multiply_all(x, sent, skip=n, transpose=True), n)
            return z.T @ z

        w, v = np.linalg.eigh(self._whole_pieces(width, product))
        keep = [k for k in range(width)[::-1][:rank] if w[k] > 1e-14 * w[-1]]
        u = self.project(n, factors, v[:, keep] / np.sqrt(w[keep]))
        return u @ polish_map(u.T @ u)

    def norm2(self) -> float:
        self.passes.reads += 1

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            yield pa.RecordBatch.from_arrays([pa.array([float(sum((x * x).sum() for _, x in _blocks(batches)))])], ["x"])

        return float(self.df.mapInArrow(run, "x double").agg(F.sum("x")).first()[0] or 0)

    def dense(self) -> np.ndarray:
        if prod(self.shape) > DRIVER_NUMBERS:
            raise ValueError("too many cells for the driver")
        out = np.zeros(self.shape)
        for r in self.df.collect():
            x = np.frombuffer(r["data"]).reshape(r["dims"])
            out[tuple(slice(a, a + s) for a, s in zip(r["lo"], x.shape, strict=True))] += x
        return out

    def kept(self) -> BlockTensor:
        from ..sources.storage import stored

        # A page for each block: else the writer looks at a page's size only after 100 rows, and packs it whole, outside the heap.
        return BlockTensor(stored(self.df, **{"parquet.page.row.count.limit": "1"}), self.shape, self.passes, self.tall)

    def to_cells(self) -> CooTensor:
        order = self.order

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for lo, x in _blocks(batches):
                at = np.nonzero(x)
                yield pa.RecordBatch.from_arrays([*(pa.array(a + c) for a, c in zip(lo, at, strict=True)), pa.array(x[at])], [*[f"i{k + 1}" for k in range(order)], "v"])

        schema = ", ".join([*[f"i{k + 1} long" for k in range(order)], "v double"])
        return CooTensor(self.df.mapInArrow(run, schema), self.shape, self.passes)


def plan_grid(shape: Sequence[int], target_bytes: int = 32 << 20) -> tuple[int, ...]:
    """Halve the longest side of a block until a block fits: more blocks than cores is fine, blocks beyond memory are not."""
    grid = [1] * len(shape)
    while 8 * prod(ceil(s / g) for s, g in zip(shape, grid, strict=True)) > target_bytes:
        k = max(range(len(shape)), key=lambda k: shape[k] / grid[k])
        grid[k] *= 2
    return tuple(min(g, s) for g, s in zip(grid, shape, strict=True))


def generated(spark: SparkSession, shape: Sequence[int], grid: Sequence[int], make: Callable[[list[int], list[int]], np.ndarray], sigma: float = 0.0, seed: int = 1) -> BlockTensor:
    """Blocks made where they are needed: make(lo, dims) plus noise that follows from seed and coordinates."""
    cuts = [cut_points(s, g) for s, g in zip(shape, grid, strict=True)]
    n_blocks = prod(grid)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in batch.column(0).to_pylist():
                s = np.unravel_index(b, grid)
                lo = [int(cuts[k][i]) for k, i in enumerate(s)]
                dims = [int(cuts[k][i + 1]) - lo[k] for k, i in enumerate(s)]
                x = make(lo, dims)
                if sigma:
                    axes = np.ix_(*[np.arange(a, a + d) for a, d in zip(lo, dims, strict=True)])
                    x = x + sigma * gauss(seed, axes)
                yield pa.RecordBatch.from_arrays([pa.array([lo], pa.list_(pa.int64())), pa.array([dims], pa.list_(pa.int64())), pa.array([np.ascontiguousarray(x).tobytes()], pa.binary())], ["lo", "dims", "data"])

    ids = spark.range(n_blocks, numPartitions=n_blocks)
    return BlockTensor(ids.mapInArrow(run, BLOCK), tuple(shape))
