"""Counter-based random numbers: the value of a cell follows from (seed, coordinates) alone.

The same integers come from numpy, from a Spark Column and from SQL text, so a sketch never depends on partitioning
and no random matrix is ever stored or sent.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# Fixed values of the mixing steps: products stay under 2^63, as ANSI mode needs.
P = 2**31 - 1
FACTOR, STEPS, CLOSING = 69621, (1013904223, 271828), (11, 29, 47)
SECOND = 7919


def mix(seed: int, coords: Sequence[np.ndarray]) -> np.ndarray:
    """31-bit hash of broadcastable integer coordinates."""
    h = np.int64(seed % P)
    for c in [*coords, *CLOSING]:
        c = np.asarray(c, np.int64) % P * FACTOR
        for add in STEPS:
            h = (h * h % P + c + add) % P
    return h


def uniform(seed: int, coords: Sequence[np.ndarray]) -> np.ndarray:
    return (mix(seed, coords) + 0.5) / P


def gauss(seed: int, coords: Sequence[np.ndarray]) -> np.ndarray:
    """Standard normal by the cosine branch of Box-Muller."""
    return np.sqrt(-2 * np.log(uniform(seed, coords))) * np.cos(2 * np.pi * uniform(seed + SECOND, coords))


def signs(seed: int, coords: Sequence[np.ndarray]) -> np.ndarray:
    return 1.0 - 2.0 * (mix(seed, coords) % 2)


def draw(dist: str, seed: int, coords: Sequence[np.ndarray]) -> np.ndarray:
    return (gauss if dist == "gaussian" else signs)(seed, coords)


def mix_col(seed: int, coords: Sequence[Column]) -> Column:
    """The same hash as a Column; an array fold, so that no step doubles the expression."""

    def half(h: Column, c: Column, add: int) -> Column:
        return F.aggregate(F.array(h), F.lit(0).cast("long"), lambda _, x: (x * x % P + c % P * FACTOR + add) % P)

    def step(h: Column, c: Column) -> Column:
        return half(half(h, c, STEPS[0]), c, STEPS[1])

    items = F.array(*[c.cast("long") for c in coords], *[F.lit(c).cast("long") for c in CLOSING])
    return F.aggregate(items, F.lit(seed % P).cast("long"), step)


def gauss_col(seed: int, coords: Sequence[Column]) -> Column:
    u, w = ((mix_col(s, coords) + F.lit(0.5)) / F.lit(float(P)) for s in (seed, seed + SECOND))
    return F.sqrt(-2 * F.ln(u)) * F.cos(2 * F.pi() * w)


def sign_col(seed: int, coords: Sequence[Column]) -> Column:
    return F.lit(1) - 2 * (mix_col(seed, coords) % 2)


def mix_sql(seed: int, coords: Sequence[str]) -> str:
    """The same hash as nested SQL; list_reduce keeps each step's value under one name."""
    items = ", ".join(f"CAST({c} AS BIGINT)" for c in [*coords, *CLOSING])
    one = f"(h * h % {P} + c % {P} * {FACTOR} + {STEPS[0]}) % {P}"
    both = f"list_reduce([{one}, 0], lambda a, z: (a * a % {P} + c % {P} * {FACTOR} + {STEPS[1]}) % {P})"
    return f"list_reduce([CAST({seed % P} AS BIGINT), {items}], lambda h, c: {both})"
