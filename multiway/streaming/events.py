"""Event streams to cells and sketches.

A sketch is linear in the tensor, so batches add up: the state of a stream is the sum of its batches' sketches, late rows
are further addends and corrections are signed ones.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.counter import sign_col
from ..sources.storage import new_path


def source(spark: SparkSession, sf_dir: str, table: str = "events", files: int = 1) -> DataFrame:
    """Rows as a stream. Event time must have a time zone for watermarks; results give it back without one."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def in_files(spark: SparkSession, parts: list[DataFrame]) -> DataFrame:
    """A stream that reads one part a micro-batch, in order: each part is a file, written after the one before."""
    path = new_path(spark, "arrivals")
    for part in parts:
        part.coalesce(1).write.mode("append").parquet(path)
    rows = spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def by_day(events: DataFrame, files: int = 5) -> list[DataFrame]:
    """Events cut into parts of equal spans of time."""
    first, last = events.agg(F.min("ts"), F.max("ts")).first()
    cuts = [first + (last - first) * k / files for k in range(1, files)]
    bounds = [None, *cuts, None]
    return [events.filter((F.lit(a is None) | (F.col("ts") >= F.lit(a))) & (F.lit(b is None) | (F.col("ts") < F.lit(b)))) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]


def _plain(time: Column) -> Column:
    return time.cast("timestamp_ntz").alias("start")


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run over all that is there, into files of the shared folder, and read the result as a table."""
    spark, out, state = stream.sparkSession, new_path(stream.sparkSession, "stream"), new_path(stream.sparkSession, "state")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{number}")

    run = stream.writeStream.outputMode(mode).option("checkpointLocation", state).foreachBatch(keep).trigger(availableNow=True).start()
    run.awaitTermination()
    if mode == "complete":  # every batch is the whole result; the last one counts
        last = run.lastProgress["batchId"]
        for number in range(last, -1, -1):
            try:
                return spark.read.schema(stream.schema).parquet(f"{out}/{number}")
            except Exception as e:  # a trigger without data writes nothing
                if "PATH_NOT_FOUND" not in str(e):
                    raise
    return spark.read.schema(stream.schema).parquet(f"{out}/*")


def tumbling(stream: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    w = F.window("ts", width)
    return stream.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(_plain(F.col("window.start")), "event_type", "n")


def sliding(stream: DataFrame, width: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n")).select(_plain(F.col("window.start")), "n")


def sessions(stream: DataFrame, gap: str = "2 hours") -> DataFrame:
    return stream.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", _plain(F.col("session_window.start")), "n")


def first_of_each(stream: DataFrame, keys: list[str]) -> DataFrame:
    return stream.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(keys)


def sketch_addend(cells: DataFrame, rank: int, seed: int) -> DataFrame:
    """A batch's sketch of the user mode of user x type x hour, with signs that follow from the coordinates."""
    names = [f"z{r}" for r in range(rank)]
    sums = [F.sum(F.col("v") * sign_col(seed, [F.col("event_type_index"), F.col("hour"), F.lit(r)])).alias(n) for r, n in enumerate(names)]
    return cells.groupBy("user_id").agg(*sums)


def event_cells(events: DataFrame) -> DataFrame:
    kind = F.ascii(F.substring("event_type", 1, 1))
    return events.select("user_id", kind.cast("long").alias("event_type_index"), F.hour("ts").cast("long").alias("hour"), F.lit(1).cast("long").alias("v"))


class SketchState:
    """Addends of all batches, by batch number, so a batch that runs again replaces itself."""

    def __init__(self, spark: SparkSession, rank: int = 4, seed: int = 9):
        self.spark, self.path, self.rank, self.seed = spark, new_path(spark, "sketch"), rank, seed

    def fold(self, batch: DataFrame, number: int) -> None:
        sketch_addend(event_cells(batch), self.rank, self.seed).write.mode("overwrite").parquet(f"{self.path}/{number}")

    def total(self) -> DataFrame:
        parts = self.spark.read.parquet(f"{self.path}/*")
        return parts.groupBy("user_id").agg(*[F.sum(f"z{r}").alias(f"z{r}") for r in range(self.rank)])

    def basis(self) -> np.ndarray:
        """A basis of the user mode from the sketch so far: what a model is refreshed from."""
        from ..operators.orth import orth

        rows = self.total().orderBy("user_id").collect()
        return orth(np.array([[r[f"z{k}"] for k in range(self.rank)] for r in rows], float))


def run_batches(stream: DataFrame, fold: Callable[[DataFrame, int], None]) -> None:
    state = new_path(stream.sparkSession, "state")
    stream.writeStream.option("checkpointLocation", state).foreachBatch(fold).trigger(availableNow=True).start().awaitTermination()
