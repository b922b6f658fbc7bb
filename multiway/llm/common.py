"""Helpers shared by the training-data operators: stored cuts of a plan, bounded Arrow slices, hashing."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that one slice of an Arrow batch may hold before Python objects are made of it.
SLICE_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that all executors share. One of our own is only made for a local session, as in tests."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        path = spark.conf.get("spark.checkpoint.dir", None)
        if path is None and not sc.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(path or tempfile.mkdtemp(prefix="mw-checkpoint-"))
    return sc.getCheckpointDir()


def stored(df: DataFrame, *, codec: str = "zstd") -> DataFrame:
    """Cut the lineage: write df as Parquet in the shared folder and read it again.

    Survives the loss of executors, and is smaller than an RDD checkpoint because it is columnar and compressed.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.cut_path = path
    return out


def discard(df: DataFrame | None) -> None:
    """Delete the files of a stored() table that nothing reads any more."""
    path = getattr(df, "cut_path", None)
    if path:
        jvm = df.sparkSession._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(where, True)


#: Keys whose rows lookup() keeps away from the exchange; any other key then has less than 1/256 of the rows.
HOT_KEYS, HOT_ROWS = 256, 1000


def lookup(left: DataFrame, right: DataFrame, key: str, how: str = "left") -> DataFrame:
    """Join `right`, which has one row a key, to `left`, where one key may hold a third of all rows.

    The at most HOT_KEYS most frequent keys of `left` meet their rows of `right` by a broadcast of so many rows; the others by an
    exchange, in which no key is large. how: left or inner; keys are not null.
    """
    spark = left.sparkSession
    most = left.filter(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("_n")).filter(f"_n >= {HOT_ROWS}").orderBy(F.desc("_n")).limit(HOT_KEYS).select(key).collect()
    if not most:
        return left.join(right, key, how)
    hot = F.broadcast(spark.createDataFrame(most, left.select(key).schema))
    few = F.broadcast(right.join(hot, key, "left_semi"))
    return left.join(hot, key, "left_anti").join(right, key, how).unionByName(left.join(hot, key, "left_semi").join(few, key, how))


def boxed(docs: DataFrame, keep: list[str], text_col: str = "text") -> DataFrame:
    """`row`, a structure of the kept columns, and `text`: whatever the columns are called, no name can clash."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"), F.col(text_col).cast("string").alias("text"))


def unboxed(df: DataFrame, *more) -> DataFrame:
    """The columns of `row`, and others if named."""
    names = df.schema["row"].dataType.names
    return df.select(*[F.col("row")[c].alias(c) for c in names], *more)


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows whose texts hold at most `limit` bytes together (one row at least)."""
    if not batch.num_rows:
        return
    size = batch.column(batch.schema.get_field_index(column)).nbytes
    if size <= limit:
        yield batch
        return
    import pyarrow.compute as pc

    lengths = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(column))), 0).to_numpy(zero_copy_only=False)
    ends, start, total = np.cumsum(lengths), 0, 0
    while start < batch.num_rows:
        stop = max(start + 1, int(np.searchsorted(ends, total + limit, side="right")))
        yield batch.slice(start, stop - start)
        total, start = int(ends[stop - 1]), stop


def trimmed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Give freed memory back to the system when a kernel ends: Python workers live on and share an executor's limit."""
    yield from batches
    import ctypes

    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # not glibc
        pass
    pa.default_memory_pool().release_unused()


def sliced_texts(batches: Iterator[pa.RecordBatch], column: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield from slices(batch, column)


class WordHashes(dict):
    """64-bit xxHash of each word seen, kept for at most `room` words."""

    def __init__(self, seed: int = 0, room: int = 400_000):
        super().__init__()
        self.seed, self.room = seed, room

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.room:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word, self.seed)
        return value

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


#: Odd multipliers of the rolling combination; any odd 64-bit numbers with mixed bits serve.
MULTIPLIERS = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F))


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    return x


def window_hashes(hashes: np.ndarray, width: int, multiplier: np.uint64 = MULTIPLIERS[0]) -> np.ndarray:
    """Hash of every run of `width` consecutive word hashes; empty when there are fewer words."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = hashes[:n].copy()
    for j in range(1, width):
        out *= multiplier
        out += hashes[j : j + n]
    return mixed(out)
