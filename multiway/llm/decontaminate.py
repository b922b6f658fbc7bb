"""Benchmark decontamination with a broadcast hash set of normalised test n-grams.

Every item becomes windows of ten consecutive words (a shorter item is one window). Words are numbered, and the windows of
each length sit in a sorted array of 64-bit hashes beside the place of one occurrence in the numbered items, so a window costs
some 20 bytes and a hit is verified word by word. The set goes to the executors, which scan the texts: words outside the
benchmark's vocabulary cut a text into runs, and only windows inside runs are looked up. A benchmark beyond `broadcast_bytes` is
cut into slices of that size, each a scan of its own whose hits are stored before the next slice is made; one aggregation
over the documents that were hit then joins them.

Defined results: words are `[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+` after A-Z became small; null and empty texts and items have none;
texts are read whole; equal windows of several items count for each; an item without an id has windows that hit, but is not
named among the items; rows repeated in either table change nothing else; an empty benchmark hits nothing; other columns may have
any name.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MULTIPLIERS, boxed, mixed, sliced_texts, stored, table, unboxed, window_hashes

WIDTH = 10
#: Text of benchmark items whose windows are broadcast at once.
BROADCAST_BYTES = 32 << 20

_WORD_BYTES = b"0123456789abcdefghijklmnopqrstuvwxyz" + bytes(range(128, 256))
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b in _WORD_BYTES else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(FOLD).split()


class Windows:
    """The hash set of a slice of items: (item, text) rows."""

    def __init__(self, items: list[tuple], width: int = WIDTH):
        self.vocabulary: dict[bytes, int] = {}
        self.names: list[str | None] = []
        numbered = []
        for item, text in items:
            numbers = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of(text)]
            if numbers:
                self.names.append(None if item is None else str(item))
                numbered.append(np.array(numbers, np.int32))
        self.words = np.concatenate(numbered) if numbered else np.empty(0, np.int32)
        sizes = np.array([len(x) for x in numbered], np.int64)
        first = np.cumsum(sizes) - sizes
        #: By length of window: sorted hashes, where each occurs in `words`, and its item.
        self.tables: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for length in sorted(set(np.minimum(sizes, width).tolist())):
            own = np.flatnonzero(np.minimum(sizes, width) == length)
            count = sizes[own] - length + 1
            item = np.repeat(own, count)
            at = np.repeat(first[own] - np.cumsum(count) + count, count) + np.arange(count.sum())
            hashes = self._hashes(self.words, length)[at]
            order = np.lexsort((item, hashes))
            self.tables[length] = (hashes[order], at[order], item[order].astype(np.int32))

    @staticmethod
    def _hashes(numbers: np.ndarray, length: int) -> np.ndarray:
        return window_hashes(mixed(numbers.astype(np.uint64) * MULTIPLIERS[1] + np.uint64(1)), length)

    @property
    def nbytes(self) -> int:
        return self.words.nbytes + sum(x.nbytes for t in self.tables.values() for x in t)

    def hits(self, words: list[bytes]) -> tuple[np.ndarray, set[int]]:
        """Which words are inside an occurrence of a window, and the numbers of the items whose windows occur."""
        n = len(words)
        numbers = np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.int32, n)
        edges, found = np.zeros(n + 1, np.int64), set()
        known = np.concatenate([[0], np.cumsum(numbers > 0)])
        for length, (hashes, at, item) in self.tables.items():
            if length > n:
                break
            starts = np.flatnonzero(known[length:] - known[:-length] == length)
            if not len(starts):
                continue
            own = self._hashes(numbers, length)[starts]
            low, high = np.searchsorted(hashes, own), np.searchsorted(hashes, own, side="right")
            for i, a, b in zip(starts[high > low].tolist(), low[high > low].tolist(), high[high > low].tolist(), strict=True):
                window = numbers[i : i + length]
                same = [k for k in range(a, b) if (self.words[at[k] : at[k] + length] == window).all()]
                if same:
                    found.update(item[same].tolist())
                    edges[i] += 1
                    edges[i + length] -= 1
        return np.cumsum(edges)[:-1] > 0, found


def _item_slices(benchmark: DataFrame, limit: int) -> list[DataFrame]:
    """Items in slices of about `limit` text bytes (one item at least), to be fetched one at a time."""
    rows = benchmark.select("item_id", F.col("text").cast("string").alias("text")).filter("text IS NOT NULL AND text <> ''")
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-total // limit))
    return [(rows if n == 1 else rows.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)).distinct() for k in range(n)]


def _windows(items: DataFrame, width: int) -> Windows:
    return Windows([(r["item_id"], r["text"]) for r in items.toLocalIterator()], width)


def scan(boxed_docs: DataFrame, windows: Windows) -> DataFrame:
    """row, n_words, hit_ranges (of words, flat start and stop), hit_items (names): no shuffle."""
    shared = boxed_docs.sparkSession.sparkContext.broadcast(windows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = shared.value
        for batch in sliced_texts(batches, "text"):
            counts, ranges, items = [], [], []
            for text in batch.column("text").to_pylist():
                words = words_of(text)
                hit, found = w.hits(words)
                names = [w.names[k] for k in found]
                counts.append(len(words))
                ranges.append(np.flatnonzero(np.diff(np.concatenate([[False], hit, [False]]).astype(np.int8))).tolist() if found else [])
                items.append(sorted({x for x in names if x is not None}))
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(counts, pa.int64()), pa.array(ranges, pa.list_(pa.int64())), pa.array(items, pa.list_(pa.string()))], ["row", "n_words", "hit_ranges", "hit_items"])

    schema = boxed_docs.select("row").schema
    return boxed_docs.mapInArrow(run, schema.add("n_words", "long").add("hit_ranges", T.ArrayType(T.LongType())).add("hit_items", T.ArrayType(T.StringType())))


def decontaminate(docs: DataFrame, benchmark: DataFrame, keep: list[str], width: int = WIDTH, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """row (the kept columns), n_words, n_hit, hit_ranges, hit_items of each document row.

    One slice: one scan without a shuffle. More: rows get a key, each slice stores the rows it hits, and one aggregation joins them.
    """
    chosen, slices = boxed(docs, keep), _item_slices(benchmark, broadcast_bytes)
    if len(slices) == 1:
        found = scan(chosen, _windows(slices[0], width))
        return found.select("row", "n_words", _covered("hit_ranges").alias("n_hit"), "hit_ranges", "hit_items")
    keyed = stored(chosen.withColumn("key", F.monotonically_increasing_id()))
    only_key = keyed.select(F.struct("key").alias("row"), "text")
    parts = [stored(scan(only_key, _windows(items, width)).filter(F.size("hit_ranges") > 0).select("row.key", "hit_ranges", "hit_items")) for items in slices]
    union = parts[0]
    for p in parts[1:]:
        union = union.unionByName(p)
    merged = union.groupBy("key").agg(F.flatten(F.collect_list("hit_ranges")).alias("_all"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("hit_items")))).alias("hit_items"))
    pairs = F.array_sort(F.transform(F.sequence(F.lit(0), (F.size("_all") / 2).cast("int") - 1), lambda i: F.struct(F.element_at("_all", 2 * i + 1).alias("a"), F.element_at("_all", 2 * i + 2).alias("b"))))
    joined = F.aggregate(pairs, F.array().cast("array<bigint>"), lambda acc, p: F.when((F.size(acc) > 0) & (F.element_at(acc, -1) >= p["a"]), F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.greatest(F.element_at(acc, -1), p["b"])))).otherwise(F.concat(acc, F.array(p["a"], p["b"]))))
    merged = merged.select("key", joined.alias("hit_ranges"), "hit_items")
    nothing = F.array()
    counted = scan(keyed.select(F.struct("key", "row").alias("row"), "text"), Windows([], width)).select("row.key", F.col("row.row").alias("row"), "n_words")
    out = counted.join(merged, "key", "left").select("row", "n_words", F.coalesce("hit_ranges", nothing.cast("array<bigint>")).alias("hit_ranges"), F.coalesce("hit_items", nothing.cast("array<string>")).alias("hit_items"))
    return out.select("row", "n_words", _covered("hit_ranges").alias("n_hit"), "hit_ranges", "hit_items")


def _covered(ranges: str):
    """Words in flat (start, stop) ranges: stops minus starts."""
    return F.aggregate(F.transform(ranges, lambda x, i: F.when(i % 2 == 0, -x).otherwise(x)), F.lit(0).cast("long"), lambda a, x: a + x)


def without_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Documents without a hit, with all their columns."""
    return unboxed(decontaminate(docs, benchmark, docs.columns).filter("n_hit = 0"))


def span_spaces(text: str, ranges: list[int]) -> str:
    """The text without the words in the ranges (white space and punctuation around them stay)."""
    import re

    spans = [m.span() for m in re.finditer(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", text)]
    out, at = [], 0
    for a, b in zip(ranges[::2], ranges[1::2], strict=True):
        out.append(text[at : spans[a][0]])
        at = spans[b - 1][1]
    return "".join([*out, text[at:]])


def without_spans(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """All documents, the hit words cut out of their texts."""
    found = decontaminate(docs, benchmark, docs.columns).withColumn("text", F.col("row")["text"].cast("string"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t if not r else span_spaces(t, r) for t, r in zip(batch.column("text").to_pylist(), batch.column("hit_ranges").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(texts, pa.string())], ["row", "text"])

    texts = found.select("row", "text", "hit_ranges").mapInArrow(cut, found.select("row", "text").schema)
    return texts.select(*[F.col("text") if c == "text" else F.col("row")[c].alias(c) for c in docs.columns])


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), ["doc_id"])
    return unboxed(found, "n_words", "n_hit", F.size("hit_items").cast("long").alias("n_items"), F.sha2(F.array_join("hit_items", ",").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


_SQL_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
SQL = f"""
WITH b AS (SELECT item_id, {_SQL_WORDS} AS ws FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, least(len(ws), {WIDTH}) AS k, array_to_string(ws[i : i + least(len(ws), {WIDTH}) - 1], ' ') AS w
  FROM (SELECT item_id, ws, unnest(range(1, greatest(len(ws) - {WIDTH} + 1, 1) + 1)) AS i FROM b WHERE len(ws) > 0)
),
ks AS (SELECT DISTINCT k FROM bw),
d AS (SELECT doc_id, {_SQL_WORDS} AS ws FROM documents),
dw AS (SELECT doc_id, k, i, array_to_string(ws[i : i + k - 1], ' ') AS w FROM (SELECT doc_id, ws, k, unnest(range(1, len(ws) - k + 2)) AS i FROM d, ks WHERE len(ws) >= k)),
hits AS (SELECT dw.doc_id, dw.i, dw.k, bw.item_id FROM dw JOIN bw ON dw.k = bw.k AND dw.w = bw.w),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM hits) GROUP BY doc_id),
its AS (SELECT doc_id, count(s) AS n_items, string_agg(s, ',' ORDER BY s) AS s FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hits) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.ws) AS BIGINT) AS n_words, coalesce(c.n_hit, 0) AS n_hit, coalesce(t.n_items, 0) AS n_items,
  sha256(coalesce(t.s, '')) AS items_sha256, coalesce(c.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN covered c ON c.doc_id = d.doc_id LEFT JOIN its t ON t.doc_id = d.doc_id
"""
