"""Index arithmetic: the first index is the fastest, everything counts from 0."""

from __future__ import annotations

from collections.abc import Sequence
from math import prod

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def strides(shape: Sequence[int], skip: int | None = None) -> list[int]:
    """Weight of each index in the linear index (0 for the skipped mode)."""
    out, step = [], 1
    for k, size in enumerate(shape):
        out.append(0 if k == skip else step)
        step *= 1 if k == skip else size
    return out


def sub2ind(coords: Sequence[Column] | Sequence[int], shape: Sequence[int], skip: int | None = None):
    """Linear index of coordinates (Columns or numbers); with skip, the column of that mode's unfolding."""
    total = None
    for c, w in zip(coords, strides(shape, skip), strict=True):
        if w:
            total = c * w if total is None else total + c * w
    return total


def ind2sub(index, shape: Sequence[int], skip: int | None = None) -> list:
    """Coordinates of a linear index (Column, number or array)."""
    out = []
    for k, (size, w) in enumerate(zip(shape, strides(shape, skip), strict=True)):
        if k == skip:
            out.append(None)
        elif isinstance(index, Column):
            out.append((F.floor(index / F.lit(w)) % size).cast("long") if w > 1 else (index % size).cast("long"))
        else:
            out.append(index // w % size)
    return out


def unfold(cells: DataFrame, shape: Sequence[int], n: int) -> DataFrame:
    """(row, col, v) of the mode-n unfolding: a projection, nothing moves."""
    coords = [F.col(f"i{k + 1}") for k in range(len(shape))]
    if prod(s for k, s in enumerate(shape) if k != n) >= 2**63:
        raise ValueError("the column index of this unfolding leaves 63 bits; use the coordinates themselves")
    return cells.select(coords[n].alias("row"), sub2ind(coords, shape, n).cast("long").alias("col"), "v")


def fold(matrix: DataFrame, shape: Sequence[int], n: int) -> DataFrame:
    """Cells of a mode-n unfolding."""
    coords = ind2sub(F.col("col"), shape, n)
    return matrix.select(*[(F.col("row") if k == n else c).alias(f"i{k + 1}") for k, c in enumerate(coords)], "v")


def permute(cells: DataFrame, order: Sequence[int]) -> DataFrame:
    return cells.select(*[F.col(f"i{k + 1}").alias(f"i{j + 1}") for j, k in enumerate(order)], "v")


def resource_matrix(grid: Sequence[int], n: int) -> np.ndarray:
    """Workers (numbered from 1) laid out as the mode-n unfolding of the grid."""
    ids = np.arange(1, prod(grid) + 1).reshape(grid, order="F")
    return np.moveaxis(ids, n, 0).reshape(grid[n], -1, order="F")


def workers(spark: SparkSession, grid: Sequence[int], n: int) -> DataFrame:
    """Each worker of a grid: its block coordinates and its place in the mode-n unfolding, all from 1."""
    return workers_of(spark.range(prod(grid)), grid, n)


def workers_of(rows: DataFrame, grid: Sequence[int], n: int) -> DataFrame:
    """Rows with the number of a worker (id, from 0): the worker, its block coordinates and its place in the mode-n unfolding, all from 1."""
    coords = ind2sub(F.col("id"), grid)
    out = rows.withColumns({"worker": F.col("id") + 1} | {f"s{k + 1}": c + 1 for k, c in enumerate(coords)}).drop("id")
    column = sub2ind([F.col(f"s{k + 1}") - 1 for k in range(len(grid))], grid, n) + 1
    return out.withColumn("unfold_row", F.col(f"s{n + 1}")).withColumn("unfold_col", column)
