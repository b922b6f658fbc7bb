"""All registered queries of the tensor engine and the SQL they are held against."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels, methods, streams, surrounding  # noqa: F401  they register themselves
from .base import ORACLE, QUERIES, built

__all__ = ["ORACLE", "QUERIES", "flagship"]


def flagship(spark: SparkSession, sf_dir: str, rank: int = 3) -> DataFrame:
    """Components of nation x brand x month: sketch to Tucker form, nonnegative CP on the form, keys beside weights."""
    from ..operators.cp import component_frame, compressed_cp
    from ..operators.tucker import sketch_tucker

    t, dictionaries = built(spark, sf_dir, "business")
    form = sketch_tucker(t, [rank + 2] * t.order, 5, "sequential")
    model = compressed_cp(form, rank, "hals", max_iter=200)
    keys = None
    for n, (name, d) in enumerate(dictionaries.items()):
        own = d.select(F.lit(n).alias("mode"), F.lit(name).alias("mode_name"), F.col("idx").alias("i"), F.col("key").cast("string").alias("key"))
        keys = own if keys is None else keys.unionByName(own)
    return component_frame(spark, model).join(F.broadcast(keys), ["mode", "i"]).select("mode", "mode_name", "key", F.col("r").alias("component"), "v", "weight")


QUERIES["flagship"] = flagship
