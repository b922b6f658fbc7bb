"""Operation, memory and communication counts, and the planner that uses them."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def gradient_flops(shape: Sequence[int], rank: int, sizes: Sequence[int] | None = None) -> float:
    """One mode's gradient: over all cells, or (with the sizes of a Tucker form) over bases and core."""
    if sizes is None:
        return float(rank) * prod(map(float, shape))
    return max(map(float, shape)) * max(sizes) ** 2 + float(max(sizes)) * prod(map(float, sizes))


def full_numbers(shape: Sequence[int]) -> float:
    return prod(map(float, shape))


def form_numbers(shape: Sequence[int], sizes: Sequence[int]) -> float:
    return prod(map(float, sizes)) + sum(float(s) * r for s, r in zip(shape, sizes, strict=True))


def passes(method: str, order: int, longest: int = 0, rank: int = 1, sweeps: int = 2, iterations: int = 1) -> int:
    """Readings of the data: each mode once (shrinking), each mode of each sweep, replicas by what they must determine."""
    return {"sequential": order, "two_sweep": sweeps * order, "hosvd": order + 1, "direct": order * iterations, "compressed": 0, "replicas": -(-longest // max(1, rank))}[method]


def omega_bytes(shape: Sequence[int], n: int, size: int, block: Sequence[int] | None = None) -> dict[str, float]:
    """Random numbers that would be sent for one sketch, and what is sent when they are regenerated instead."""
    other = prod(float(s) for k, s in enumerate(shape) if k != n)
    tasks = 1 if block is None else prod(-(-s // b) for s, b in zip(shape, block, strict=True))
    sent = 8.0 * size * (other if block is None else prod(float(b) for k, b in enumerate(block) if k != n)) * tasks
    return {"broadcast": sent, "regenerated": 24.0 * tasks}


@dataclass
class Plan:
    layout: str
    method: str
    mode_order: tuple[int, ...]
    why: str

    def explain(self) -> str:
        return f"layout {self.layout}, method {self.method}, modes {self.mode_order}: {self.why}"


def mode_order(shape: Sequence[int], sizes: Sequence[int]) -> tuple[int, ...]:
    """The mode that shrinks most goes first: the first product decides the cost."""
    return tuple(sorted(range(len(shape)), key=lambda n: sizes[n] / shape[n]))


def choose(cells: DataFrame, shape: Sequence[int], sizes: Sequence[int], dense_share: float = 0.2) -> Plan:
    """Blocks for dense data; for sparse data the sweeps, unless fibers are filled so well that products shrink them.

    A product turns every cell of a fiber into one row of sizes[n] cells: with fewer cells a fiber than that, data grows.
    """
    order = mode_order(shape, sizes)
    others = [f"i{k + 1}" for k in range(len(shape)) if k != order[0]]
    row = cells.agg(F.count("*").alias("n"), F.approx_count_distinct(F.struct(*others)).alias("fibers")).first()
    share = row["n"] / full_numbers(shape)
    filled = row["n"] / max(1, row["fibers"])
    if share >= dense_share:
        return Plan("blocks", "two_sweep", order, f"{share:.0%} of the cells are stored")
    if filled < sizes[order[0]]:
        return Plan("cells", "two_sweep", order, f"{filled:.1f} cells a fiber against {sizes[order[0]]} components: a product would grow the data")
    return Plan("cells", "sequential", order, f"{filled:.1f} cells a fiber against {sizes[order[0]]} components: products shrink the data")
