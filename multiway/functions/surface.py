"""Functions for SQL users, and a join that spreads hot keys."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def dot(a: pd.Series, b: pd.Series) -> pd.Series:
    """Inner product of two arrays."""
    return pd.Series([float(np.dot(np.asarray(x, float), np.asarray(y, float))) for x, y in zip(a, b, strict=True)])


def gram_entry(a: Column, b: Column) -> Column:
    """One entry of a Gram, as an aggregate of built-in functions."""
    return F.sum(a * b)


class Cells:
    """Cells of an array laid out in rows of `side`."""

    def eval(self, values: list[float], side: int) -> Iterator[tuple[int, int, float]]:
        for p, v in enumerate(values or []):
            yield p // side, p % side, v


def register(spark: SparkSession) -> SparkSession:
    """mw_dot, mw_cells, mw_ind2sub and mw_fit for SQL in this session."""
    spark.udf.register("mw_dot", F.pandas_udf(dot, "double"))
    spark.udtf.register("mw_cells", F.udtf(Cells, returnType="i bigint, j bigint, v double"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mw_ind2sub(id BIGINT, step BIGINT, size BIGINT) RETURNS BIGINT RETURN (id DIV step) % size")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mw_fit(norm2 DOUBLE, core2 DOUBLE) RETURNS DOUBLE RETURN 1 - sqrt(greatest(0D, norm2 - core2) / norm2)")
    return spark


def salted_join(left: DataFrame, right: DataFrame, left_key: str, right_key: str, salts: int) -> DataFrame:
    """Inner join whose left rows of one key go to `salts` tasks; the right side, a row a key, is repeated for each."""
    spread = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    copies = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return spread.join(copies, (spread[left_key] == copies[right_key]) & (spread["_salt"] == copies["_salt"])).drop("_salt")
