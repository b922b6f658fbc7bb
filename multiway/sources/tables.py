"""Tensors from tables: cells are one aggregation over the joined facts, indices come from dictionaries of the keys."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.tensors import CooTensor
from .storage import stored


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def dictionary(keys: DataFrame, key: str, large: bool = False) -> DataFrame:
    """(idx, key): dense ranks from 0. large: ranks by range partition and offsets, so no task sees all keys."""
    distinct = keys.select(key).filter(F.col(key).isNotNull()).distinct()
    if not large:
        return distinct.select((F.row_number().over(Window.orderBy(key)) - 1).cast("long").alias("idx"), F.col(key).alias("key"))
    placed = stored(distinct.repartitionByRange(key).withColumn("_p", F.spark_partition_id()))
    counts = placed.groupBy("_p").agg(F.count("*").alias("n")).orderBy("_p").collect()
    offsets, total = [], 0
    for r in counts:
        offsets.append((r["_p"], total))
        total += r["n"]
    first = placed.sparkSession.createDataFrame(offsets, "_p int, _first long")
    rank = F.row_number().over(Window.partitionBy("_p").orderBy(key)) - 1
    return placed.withColumn("_r", rank).join(F.broadcast(first), "_p").select((F.col("_first") + F.col("_r")).alias("idx"), F.col(key).alias("key"))


def keyed_cells(facts: DataFrame, modes: Sequence[tuple[str, Column]], value: Column, agg: str = "sum") -> DataFrame:
    """One row for each combination of keys; null keys and null values take no part."""
    rows = facts.select(*[c.alias(n) for n, c in modes], value.cast("double").alias("v")).dropna()
    fold = {"sum": F.sum, "avg": F.avg, "max": F.max, "min": F.min}.get(agg)
    cells = rows.groupBy(*[n for n, _ in modes]).agg((F.count("*").cast("double") if agg == "count" else fold("v")).alias("v"))
    return cells


def from_table(facts: DataFrame, modes: Sequence[tuple[str, Column]], value: Column, agg: str = "sum", large: Sequence[str] = ()) -> tuple[CooTensor, dict[str, DataFrame]]:
    """A tensor and the dictionary of each mode."""
    cells = stored(keyed_cells(facts, modes, value, agg))
    dictionaries, shape = {}, []
    for k, (name, _) in enumerate(modes):
        d = stored(dictionary(cells, name, name in large))
        shape.append(d.count())
        own = d.select(F.col("idx").alias(f"i{k + 1}"), F.col("key").alias(name))
        cells = cells.join(own, name)
        dictionaries[name] = d
    return CooTensor(cells.select(*[f"i{k + 1}" for k in range(len(modes))], "v"), tuple(shape)), dictionaries


def month(c: str) -> Column:
    return F.date_format(c, "yyyy-MM")


def business(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list, Column]:
    """Supplier nation x part brand x ship month, quantities."""
    t = lambda n: table(spark, sf_dir, n)
    facts = t("lineitem").join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    return facts, [("nation", F.col("s_nationkey")), ("brand", F.col("p_brand")), ("month", month("l_shipdate"))], F.col("l_quantity")


def five_way(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list, Column]:
    """Customer nation x brand x segment x priority x ship year, quantities."""
    t = lambda n: table(spark, sf_dir, n)
    facts = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    return facts, [("nation", F.col("c_nationkey")), ("brand", F.col("p_brand")), ("segment", F.col("c_mktsegment")), ("priority", F.col("o_orderpriority")), ("year", F.year("l_shipdate"))], F.col("l_quantity")


def orders_four(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list, Column]:
    """Customer nation x segment x priority x status, counts."""
    t = lambda n: table(spark, sf_dir, n)
    facts = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    return facts, [("nation", F.col("c_nationkey")), ("segment", F.col("c_mktsegment")), ("priority", F.col("o_orderpriority")), ("status", F.col("o_orderstatus"))], F.lit(1)


def purchases(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list, Column]:
    """Part x supplier x customer, quantities: hyper-sparse."""
    t = lambda n: table(spark, sf_dir, n)
    facts = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return facts, [("part", F.col("l_partkey")), ("supplier", F.col("l_suppkey")), ("customer", F.col("o_custkey"))], F.col("l_quantity")


def activity(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list, Column]:
    """User x event type x hour of day, counts."""
    return table(spark, sf_dir, "events"), [("user", F.col("user_id")), ("event_type", F.col("event_type")), ("hour", F.hour("ts"))], F.lit(1)


#: Characters by UTF-8 byte: a-z as 0-25, all else as 26; a later byte of a character doesn't count.
LETTERS = 27
_CODE = np.full(256, LETTERS - 1, np.int16)
_CODE[ord("a") : ord("z") + 1] = _CODE[ord("A") : ord("Z") + 1] = np.arange(LETTERS - 1)
#: Bytes of text and documents that are counted at a time.
_SLICE_BYTES, _SLICE_DOCS = 4 << 20, 1024


def _pairs(texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each text the pairs of adjacent characters that it has, as 27 a + b, and their numbers."""
    ends = np.cumsum([0, *pc.binary_length(texts).to_pylist()])
    first = 0
    while first < len(texts):
        last = min(first + _SLICE_DOCS, max(first + 1, int(np.searchsorted(ends, ends[first] + _SLICE_BYTES, "right")) - 1))
        raw = np.frombuffer(b"".join(texts.slice(first, last - first).to_pylist()), np.uint8)
        owner = np.repeat(np.arange(last - first, dtype=np.int32), np.diff(ends[first : last + 1]))
        begins = (raw & 0xC0) != 0x80
        code, owner = _CODE[raw[begins]], owner[begins]
        same = owner[1:] == owner[:-1]
        key = (owner[:-1] * np.int64(LETTERS**2) + code[:-1] * LETTERS + code[1:])[same]
        counts = np.bincount(key, minlength=(last - first) * LETTERS**2).reshape(last - first, -1)
        for row in counts:
            at = np.flatnonzero(row)
            yield at, row[at]
        first = last


def bigram_rows(texts: DataFrame, id_col: str, text_col: str = "text") -> DataFrame:
    """id and an array of (p, n): pairs and numbers of each text of that id, as binary int16 and int64. Texts without a pair are left out."""
    low = texts.select(F.col(id_col).alias("id"), F.lower(F.coalesce(F.col(text_col), F.lit(""))).cast("binary").alias("t"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [(k, at.astype(np.int16).tobytes(), n.tobytes()) for k, (at, n) in enumerate(_pairs(batch.column(1))) if len(at)]
            k, p, n = zip(*found, strict=True) if found else ((), (), ())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(k, pa.int64())), pa.array(p, pa.binary()), pa.array(n, pa.binary())], ["id", "p", "n"])

    schema = T.StructType([low.schema["id"], T.StructField("p", T.BinaryType()), T.StructField("n", T.BinaryType())])
    return low.mapInArrow(run, schema).groupBy("id").agg(F.collect_list(F.struct("p", "n")).alias("own"))


def merged(own: list[dict]) -> tuple[np.ndarray, np.ndarray]:
    """Pairs and numbers of an id, whose texts may be several."""
    p, n = (np.concatenate([np.frombuffer(x[k], kind) for x in own]) for k, kind in (("p", np.int16), ("n", np.int64)))
    if len(own) == 1:
        return p, n
    total = np.bincount(p, n, LETTERS**2).astype(np.int64)
    at = np.flatnonzero(total)
    return at.astype(np.int16), total[at]


def bigrams(texts: DataFrame, id_col: str, text_col: str = "text") -> DataFrame:
    """id, a, b, n: pairs of adjacent characters, a-z as 0-25 and all else as 26."""
    rows = bigram_rows(texts, id_col, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, _SLICE_DOCS):
                part = batch.slice(lo, _SLICE_DOCS)
                found = [merged(x) for x in part.column(1).to_pylist()]
                p = np.concatenate([x for x, _ in found]).astype(np.int64)
                ids = part.column(0).take(pa.array(np.repeat(np.arange(len(found)), [len(x) for x, _ in found])))
                yield pa.RecordBatch.from_arrays([ids, pa.array(p // LETTERS), pa.array(p % LETTERS), pa.array(np.concatenate([n for _, n in found]))], ["id", "a", "b", "n"])

    return rows.mapInArrow(run, T.StructType([rows.schema["id"], *[T.StructField(c, T.LongType()) for c in "abn"]]))


def embedding_cells(spark: SparkSession, sf_dir: str, side: int = 8) -> CooTensor:
    """Vector x side x side."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("p", "x"))
    cells = e.select(F.col("vec_id").alias("i1"), F.floor(F.col("p") / side).cast("long").alias("i2"), (F.col("p") % side).cast("long").alias("i3"), F.col("x").cast("double").alias("v"))
    size = table(spark, sf_dir, "embeddings").agg(F.max("vec_id")).first()[0]
    return CooTensor(cells, ((size if size is not None else -1) + 1, side, side))
