"""Readers and writers of cells, blocks and plain files."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.tensors import BLOCK, BlockTensor
from .storage import new_path


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """Write in a format and read with the schema given."""
    path = new_path(df.sparkSession, kind)
    options = {"header": "true"} if kind == "csv" else {}
    df.write.options(**options).format(kind).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(kind).load(path)


def write_cells(cells: DataFrame, path: str, width: int) -> str:
    """Cells in folders by coarse first coordinate, sorted inside, so slices read few files and few row groups."""
    cells.withColumn("part1", F.floor(F.col("i1") / width)).repartition("part1").sortWithinPartitions("i1").write.partitionBy("part1").parquet(path)
    return path


def read_cells(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).drop("part1")


def bucketed(cells: DataFrame, key: str, buckets: int) -> DataFrame:
    """A table bucketed by a mode: later joins and sums by it need no exchange."""
    spark = cells.sparkSession
    name = new_path(spark, "t").rpartition("/")[2].replace("-", "_")
    cells.write.bucketBy(buckets, key).sortBy(key).option("path", new_path(spark, "bucketed")).saveAsTable(name)
    return spark.table(name)


def write_blocks(t: BlockTensor, path: str) -> str:
    t.df.write.parquet(path)
    return path


def read_blocks(spark: SparkSession, path: str, shape: Sequence[int]) -> BlockTensor:
    return BlockTensor(spark.read.schema(BLOCK).parquet(path), tuple(shape))


class RampSource(DataSource):
    """Cells of a small rank-one tensor, a partition for each first index: a test source that needs no files."""

    @classmethod
    def name(cls) -> str:
        return "multiway_ramp"

    def schema(self) -> str:
        order = len(self.options["shape"].split(","))
        return ", ".join([*[f"i{k + 1} bigint" for k in range(order)], "v double"])

    def reader(self, schema) -> DataSourceReader:
        return _RampReader([int(s) for s in self.options["shape"].split(",")])


class _RampReader(DataSourceReader):
    def __init__(self, shape: list[int]):
        self.shape = shape

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.shape[0])]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        at = np.indices([1, *self.shape[1:]]).reshape(len(self.shape), -1)
        at[0] += partition.value
        v = prod((at[k] + k + 1).astype(float) for k in range(len(self.shape)))
        yield pa.RecordBatch.from_arrays([*(pa.array(c.astype(np.int64)) for c in at), pa.array(v)], [*[f"i{k + 1}" for k in range(len(self.shape))], "v"])


def synthetic(spark: SparkSession, shape: Sequence[int]) -> DataFrame:
    spark.dataSource.register(RampSource)
    return spark.read.format("multiway_ramp").option("shape", ",".join(map(str, shape))).load()
