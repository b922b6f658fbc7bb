"""Substring deduplication with a log-structured index of window fingerprints.

A window is 13 consecutive words of a document. The index holds sorted immutable runs: a run is, for each bucket of the
hash space, the sorted 64-bit fingerprints of windows with the smallest document that has each and 16 bits of a second
fingerprint, from other bits of the words' 128-bit hashes, that verify a match. A new batch becomes runs of its own, one per slice
of texts; within a slice equal windows already meet, so a passage shared by millions of documents leaves each slice once. The runs
of a bucket (old ones and new ones) are merge-joined in one task, which tells each document which of its windows occur in a
document with a smaller id, and yields the bucket's new run. Buckets are as many as the measured bytes of text ask for. When a
tier has more than `fanout` runs they are compacted into one of the next tier, so a window is rewritten once a tier.

The index is recoverable: runs have names of their own and count only once a manifest names them, and each manifest is a new
version beside the old ones, so a batch that was lost half-way leaves the index as it was and can be fed again.

A batch may hold any ids; what it removes refers to documents in the index and in the batch with smaller ids. Feeding batches in
order of id gives the same as one batch of everything.

Fingerprints travel packed: sorted values as differences in variable-length bytes, so the exchange is a few bytes a window.

Defined results: words are `[^\\x20\\x09-\\x0D]+`, unchanged; null and empty texts have none; texts of under 13 words have no window
and stay whole; ties don't arise (ids compare strictly, so rows that repeat an id never remove from each other); rows
without an id keep all words and lend none; an empty table gives no rows; other columns are kept as they are and may have any
name.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MULTIPLIERS, mixed, sliced_texts, stored, table, trimmed, unboxed, window_hashes

WIDTH = 13
#: Text bytes of which one run is made.
RUN_BYTES = 8 << 20
#: Text bytes whose windows a bucket is to hold.
BUCKET_BYTES = 16 << 20
#: Runs that a tier may have before they are compacted.
FANOUT = 4


def pack_sorted(values: np.ndarray) -> bytes:
    """Sorted 64-bit values as differences: a width in bytes, the few wider ones, then so many bytes of each."""
    if not len(values):
        return b""
    steps = np.diff(values, prepend=np.uint64(0))
    # Uniform hashes have steps of much the same size; the few that need more bytes are stored apart.
    usual = int(np.partition(steps, int(0.995 * (len(steps) - 1)))[int(0.995 * (len(steps) - 1))])
    width = max(1, (usual.bit_length() + 7) // 8)
    if width >= 8:
        return bytes([8]) + steps.tobytes()
    large = np.flatnonzero(steps >> np.uint64(8 * width))
    body = np.ascontiguousarray(steps).view(np.uint8).reshape(-1, 8)[:, :width].tobytes()
    return bytes([width]) + np.uint32(len(large)).tobytes() + large.astype(np.uint32).tobytes() + steps[large].tobytes() + body


def unpack_sorted(data: bytes) -> np.ndarray:
    if not data:
        return np.empty(0, np.uint64)
    width = data[0]
    if width == 8:
        return np.cumsum(np.frombuffer(data, np.uint64, offset=1), dtype=np.uint64)
    n = int(np.frombuffer(data, np.uint32, 1, 1)[0])
    large = np.frombuffer(data, np.uint32, n, 5)
    values = np.frombuffer(data, np.uint64, n, 5 + 4 * n)
    body = np.frombuffer(data, np.uint8, offset=5 + 12 * n).reshape(-1, width)
    steps = np.zeros((len(body), 8), np.uint8)
    steps[:, :width] = body
    steps = steps.view(np.uint64).ravel().copy()
    steps[large] = values
    return np.cumsum(steps, dtype=np.uint64)


def pack_ids(ids: np.ndarray) -> bytes:
    """Sorted distinct ids (signed) for pack_sorted."""
    return pack_sorted(ids.astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63))


def unpack_ids(data: bytes) -> np.ndarray:
    return (unpack_sorted(data) ^ np.uint64(1 << 63)).view(np.int64)


def grouped(keys: np.ndarray, checks: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, ...]:
    """Entries sorted by fingerprint, where each distinct one begins, and its smallest document for every entry."""
    order = np.argsort(keys)
    k, c = keys[order], checks[order]
    same = k[1:] == k[:-1]
    if (same & (c[1:] != c[:-1])).any():  # a key shared by different windows: the check decides too
        order = np.lexsort((checks, keys))
        k, c = keys[order], checks[order]
        same = (k[1:] == k[:-1]) & (c[1:] == c[:-1])
    starts = np.flatnonzero(np.concatenate([[True], ~same])) if len(k) else np.empty(0, np.int64)
    d = docs[order]
    least = np.minimum.reduceat(d, starts) if len(starts) else d[:0]
    return order, k, c, d, starts, least


class LongHashes(dict):
    """128-bit xxHash of each word seen, kept for at most `room` words."""

    def __init__(self, room: int = 200_000):
        super().__init__()
        self.room = room

    def __missing__(self, word: bytes) -> bytes:
        if len(self) >= self.room:
            self.clear()
        value = self[word] = xxhash.xxh3_128_digest(word)
        return value


class Fingerprints:
    """Keys and checks of the windows of texts: each from its own half of the words' hashes."""

    def __init__(self, width: int = WIDTH):
        self.width, self.words = width, LongHashes()

    def of(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        halves = np.frombuffer(b"".join(map(self.words.__getitem__, words)), np.uint64).reshape(-1, 2)
        keys = window_hashes(halves[:, 0], self.width)
        other = window_hashes(halves[:, 1], self.width, MULTIPLIERS[1])
        return keys, (other >> np.uint64(48)).astype(np.uint16)


RUN_SCHEMA = "bucket int, shard int, fresh boolean, keys binary, checks binary, ids binary, places binary"
_RUN_TYPES = [pa.int32(), pa.int32(), pa.bool_(), pa.binary(), pa.binary(), pa.binary(), pa.binary()]
_RUN_NAMES = ["bucket", "shard", "fresh", "keys", "checks", "ids", "places"]


def _flag_rows(docs: np.ndarray, keys: np.ndarray, n_shards: int, bucket: int | None = None) -> list[tuple]:
    """Fingerprints to remove, packed into a row for each shard of documents: ids, how many keys each has, the keys.

    A row for each document and bucket would be many times as many rows as documents.
    """
    order = np.lexsort((keys, docs))
    docs, keys = docs[order], keys[order]
    fresh = np.concatenate([[True], (docs[1:] != docs[:-1]) | (keys[1:] != keys[:-1])]) if len(docs) else np.empty(0, bool)
    docs, keys = docs[fresh], keys[fresh]
    shard = (mixed(docs.view(np.uint64)) % np.uint64(n_shards)).astype(np.int64)
    order = np.argsort(shard, kind="stable")
    docs, keys, shard = docs[order], keys[order], shard[order]
    rows, edges = [], np.searchsorted(shard, np.arange(n_shards + 1))
    for s in np.flatnonzero(np.diff(edges)).tolist():
        d, k = docs[edges[s] : edges[s + 1]], keys[edges[s] : edges[s + 1]]
        ids, counts = np.unique(d, return_counts=True)
        rows.append((-1 - s if bucket is None else bucket, s, True, k.tobytes(), None, pack_ids(ids), counts.astype(np.uint32).tobytes()))
    return rows


def _packed_run(bucket: int, fresh: bool, keys: np.ndarray, checks: np.ndarray, docs: np.ndarray) -> tuple:
    ids, places = np.unique(docs, return_inverse=True)
    kind = np.uint16 if len(ids) <= 1 << 16 else np.uint32
    return bucket, None, fresh, pack_sorted(keys), checks.tobytes(), pack_ids(ids), places.astype(kind).tobytes()


def _unpacked_run(keys: bytes, checks: bytes, ids: bytes, places: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    k, names = unpack_sorted(keys), unpack_ids(ids)
    at = np.frombuffer(places, np.uint16 if len(names) <= 1 << 16 else np.uint32)
    return k, np.frombuffer(checks, np.uint16), names[at]


def runs_of(docs: DataFrame, n_buckets: int, width: int = WIDTH) -> DataFrame:
    """Runs of a batch (shard is null) and, by shard of documents, windows that a smaller one of the slice has (bucket < 0)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fingerprints, held, size = Fingerprints(width), [], 0

        def out() -> pa.RecordBatch:
            keys, checks, ids = (np.concatenate(x) for x in zip(*held, strict=True))
            order, k, c, d, starts, least = grouped(keys, checks, ids)
            first = np.repeat(least, np.diff(np.append(starts, len(k))))
            later = d > first
            rows = _flag_rows(d[later], k[later], n_buckets)
            k, c = k[starts], c[starts]
            bucket = ((k >> np.uint64(32)) * np.uint64(n_buckets)) >> np.uint64(32)
            edges = np.searchsorted(bucket, np.arange(n_buckets + 1))
            rows += [_packed_run(b, True, k[x:y], c[x:y], least[x:y]) for b, (x, y) in enumerate(zip(edges[:-1], edges[1:], strict=True)) if y > x]
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), _RUN_TYPES, strict=True)], _RUN_NAMES)

        for batch in sliced_texts(batches, "text"):
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                raw = text.encode()
                keys, checks = fingerprints.of(raw.split())
                if len(keys):
                    held.append((keys, checks, np.full(len(keys), doc, np.int64)))
                size += len(raw)
            if size >= RUN_BYTES and held:
                yield out()
                held, size = [], 0
        if held:
            yield out()

    return docs.filter("doc_id IS NOT NULL AND text IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lambda batches: trimmed(run(batches)), RUN_SCHEMA)


def merge_runs(runs: DataFrame, n_buckets: int, emit: str = "flags") -> DataFrame:
    """Merge-join the runs of each bucket. emit: `flags` of new documents by shard, or the new `run`."""

    def merge(group: pd.DataFrame) -> pd.DataFrame:
        if group["bucket"].iloc[0] < 0:
            return group if emit != "run" else group.iloc[:0]
        parts, fresh = [], []
        for keys, checks, ids, places, new in zip(group["keys"], group["checks"], group["ids"], group["places"], group["fresh"], strict=True):
            parts.append(_unpacked_run(keys, checks, ids, places))
            fresh.append(np.full(len(parts[-1][0]), bool(new)))
        keys, checks, docs = (np.concatenate(x) for x in zip(*parts, strict=True))
        order, k, c, d, starts, least = grouped(keys, checks, docs)
        bucket, rows = int(group["bucket"].iloc[0]), []
        if emit != "run":
            first = np.repeat(least, np.diff(np.append(starts, len(k))))
            later = (d > first) & np.concatenate(fresh)[order]
            rows += _flag_rows(d[later], k[later], n_buckets, bucket)
        else:
            rows.append(_packed_run(bucket, False, k[starts], c[starts], least))
        return pd.DataFrame(rows, columns=_RUN_NAMES)

    return runs.groupBy("bucket").applyInPandas(merge, RUN_SCHEMA)


def remove_flagged(docs: DataFrame, flags: DataFrame, n_shards: int, keep: list[str], width: int = WIDTH, original: bool = False) -> DataFrame:
    """row (the kept columns), n_words, n_removed, kept (the words left, joined by blanks; null for a null text) of each row.

    Flags and documents (texts compressed) meet by shard in one exchange: the flags of a shard come first and are held,
    its documents stream past them. Rows without an id are spread by their text.
    original: with `original`, the text as it was, for rows that lose nothing (they then have no `kept`).
    """
    import zstandard

    def shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        small = zstandard.ZstdCompressor(1)
        for batch in sliced_texts(batches, "text"):
            texts = batch.column("text").to_pylist()
            packed = pa.array([None if t is None else small.compress(t.encode()) for t in texts], pa.binary())
            ids = batch.column("id").to_pylist()
            places = mixed(np.array([xxhash.xxh32_intdigest((t or "").encode()) if i is None else i for i, t in zip(ids, texts, strict=True)], np.int64).view(np.uint64))
            yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("id"), pa.array((places % np.uint64(n_shards)).astype(np.int32)), packed], ["row", "id", "shard", "packed"])

    chosen = docs.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"), F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text"))
    packed = chosen.mapInArrow(shrink, chosen.drop("text").schema.add("shard", T.IntegerType()).add("packed", "binary"))
    lists = flags.select("shard", F.lit(0).alias("kind"), "ids", F.col("places").alias("counts"), "keys")
    met = packed.withColumn("kind", F.lit(1)).unionByName(lists, allowMissingColumns=True).repartition("shard").sortWithinPartitions("shard", "kind")
    output = ["row", "n_words", "n_removed", "kept", "original"]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        large, fingerprints, shard, flagged = zstandard.ZstdDecompressor(), Fingerprints(width), None, {}
        for whole in batches:
            for batch in (whole.slice(i, 256) for i in range(0, whole.num_rows, 256)):
                counts, removed, texts, untouched, rows = [], [], [], [], []
                for at, (own, kind, ids, numbers, keys, doc, data) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("shard", "kind", "ids", "counts", "keys", "id", "packed")), strict=True)):
                    if own != shard:
                        shard, flagged = own, {}
                    if not kind:
                        edges = np.cumsum(np.frombuffer(numbers, np.uint32))[:-1]
                        for d, part in zip(unpack_ids(ids).tolist(), np.split(np.frombuffer(keys, np.uint64), edges), strict=True):
                            flagged.setdefault(d, []).append(part)
                        continue
                    rows.append(at)
                    raw = large.decompress(data) if data is not None else b""
                    words = raw.split()
                    counts.append(len(words))
                    gone = np.zeros(len(words), bool)
                    if doc in flagged and len(words) >= width:
                        fingerprint, _ = fingerprints.of(words)
                        hit = np.flatnonzero(np.isin(fingerprint, np.concatenate(flagged[doc])))
                        edges = np.zeros(len(words) + 1, np.int64)
                        np.add.at(edges, hit, 1)
                        np.add.at(edges, hit + width, -1)
                        gone = np.cumsum(edges)[:-1] > 0
                    removed.append(int(gone.sum()))
                    if removed[-1]:
                        words = [w for w, g in zip(words, gone.tolist(), strict=True) if not g]
                    intact = original and not removed[-1]
                    texts.append(None if data is None or intact else b" ".join(words).decode())
                    untouched.append(raw.decode() if intact and data is not None else None)
                columns = [pa.array(counts, pa.int64()), pa.array(removed, pa.int64()), pa.array(texts, pa.string()), pa.array(untouched, pa.string())]
                yield pa.RecordBatch.from_arrays([batch.column("row").take(pa.array(rows, pa.int64())), *columns], output)

    schema = chosen.select("row").schema.add("n_words", "long").add("n_removed", "long").add("kept", "string").add("original", "string")
    return met.mapInArrow(lambda batches: trimmed(cut(batches)), schema)


def buckets_for(docs: DataFrame) -> int:
    """As many buckets as the measured text asks for, at least one for each shuffle partition."""
    total = docs.agg(F.sum(F.octet_length(F.col("text").cast("string")))).first()[0] or 0
    return max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-total // BUCKET_BYTES))


class SubstringIndex:
    """Runs of all batches so far, under one shared folder; the newest manifest names those that count.

    n_buckets holds for the life of an index: buckets_for() of the text it is to hold in the end.
    """

    def __init__(self, spark: SparkSession, path: str, n_buckets: int, width: int = WIDTH, fanout: int = FANOUT):
        self.spark, self.path, self.n_buckets, self.width, self.fanout = spark, path.rstrip("/"), n_buckets, width, fanout
        self.runs: list[tuple[int, str]] = []  # tier, name
        self.version = 0

    def _commit(self) -> None:
        """A new manifest beside the old ones; the task output's own commit makes it whole or absent."""
        self.version += 1
        rows = [(t, r, self.n_buckets, self.width, self.fanout) for t, r in self.runs]
        self.spark.createDataFrame(rows, "tier int, run string, n_buckets int, width int, fanout int").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/manifest-{self.version}")

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> SubstringIndex:
        """The index as its newest whole manifest says."""
        jvm, path = spark._jvm, path.rstrip("/")
        folder = jvm.org.apache.hadoop.fs.Path(path)
        files = folder.getFileSystem(spark._jsc.hadoopConfiguration())
        names = [s.getPath().getName() for s in files.listStatus(folder)]
        versions = [int(n.split("-")[1]) for n in names if n.startswith("manifest-") and files.exists(jvm.org.apache.hadoop.fs.Path(f"{path}/{n}/_SUCCESS"))]
        rows = spark.read.parquet(f"{path}/manifest-{max(versions)}").collect()
        index = cls(spark, path, rows[0]["n_buckets"], rows[0]["width"], rows[0]["fanout"])
        index.runs, index.version = sorted((r["tier"], r["run"]) for r in rows), max(versions)
        return index

    def _read(self, runs: list[tuple[int, str]]) -> DataFrame:
        return self.spark.read.schema(RUN_SCHEMA).parquet(*(f"{self.path}/{name}" for _, name in runs))

    def _write(self, runs: DataFrame) -> str:
        name = f"run-{uuid.uuid4().hex}"
        merge_runs(runs, self.n_buckets, "run").write.parquet(f"{self.path}/{name}")
        return name

    def dedup(self, docs: DataFrame, keep: list[str]) -> DataFrame:
        """remove_flagged() of a batch against the index and itself; its windows become a run of the index."""
        fresh = stored(runs_of(docs, self.n_buckets, self.width))
        flags = stored(merge_runs(fresh.unionByName(self._read(self.runs)) if self.runs else fresh, self.n_buckets))
        self.runs.append((0, self._write(fresh.filter("bucket >= 0"))))
        self.compact()
        self._commit()
        return remove_flagged(docs, flags, self.n_buckets, keep, self.width)

    def compact(self) -> None:
        """Merge the runs of every tier that has more than `fanout` into one of the next tier."""
        tier = 0
        while tier <= max(t for t, _ in self.runs):
            own = [r for r in self.runs if r[0] == tier]
            if len(own) > self.fanout:
                self.runs = [r for r in self.runs if r[0] != tier] + [(tier + 1, self._write(self._read(own)))]
            tier += 1


def dedup_batch(docs: DataFrame, keep: list[str], width: int = WIDTH, original: bool = False) -> DataFrame:
    """remove_flagged() of one batch against an empty index."""
    n = buckets_for(docs)
    return remove_flagged(docs, merge_runs(runs_of(docs, n, width), n), n, keep, width, original)


def without_repeats(docs: DataFrame) -> DataFrame:
    """All columns of documents, texts without the words of passages that a document with a smaller id has.

    A text that loses nothing stays as it is; one that does has its words joined by blanks, and its n_chars, if there is such a
    column of a number, counted anew; a document left without a word goes.
    """
    out = dedup_batch(docs, [c for c in docs.columns if c != "text"], original=True).filter("n_removed = 0 OR n_removed < n_words")
    old = F.col("row")
    new = {"text": F.when(F.col("n_removed") > 0, F.col("kept")).otherwise(F.col("original")).cast(docs.schema["text"].dataType)}
    if "n_chars" in docs.columns and isinstance(docs.schema["n_chars"].dataType, T.NumericType):
        new["n_chars"] = F.when(F.col("n_removed") > 0, F.length("kept")).otherwise(old["n_chars"]).cast(docs.schema["n_chars"].dataType)
    return out.select(*[(new[c] if c in new else old[c]).alias(c) for c in docs.columns])


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup_batch(table(spark, sf_dir, "documents"), ["doc_id"])
    return unboxed(out, "n_words", "n_removed", F.sha2(F.coalesce("kept", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


_SQL_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
SQL = f"""
WITH d AS (SELECT doc_id, {_SQL_WORDS} AS ws FROM documents),
w AS (SELECT doc_id, i, array_to_string(ws[i : i + {WIDTH - 1}], ' ') AS w FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - {WIDTH} + 2)) AS i FROM d WHERE len(ws) >= {WIDTH} AND doc_id IS NOT NULL)),
m AS (SELECT w, min(doc_id) AS first FROM w GROUP BY w),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + {WIDTH})) AS p FROM w JOIN m USING (w) WHERE w.doc_id > m.first),
words AS (SELECT doc_id, ws[p] AS x, p FROM (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS p FROM d)),
kept AS (SELECT words.doc_id, string_agg(x, ' ' ORDER BY p) AS s FROM words ANTI JOIN gone USING (doc_id, p) GROUP BY words.doc_id),
n AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.ws) AS BIGINT) AS n_words, coalesce(n.n, 0) AS n_removed, sha256(coalesce(kept.s, '')) AS kept_sha256
FROM d LEFT JOIN kept ON kept.doc_id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""
