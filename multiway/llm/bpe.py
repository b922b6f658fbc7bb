"""Byte-level BPE encoding and decoding with a segment tree of pair ranks.

Each match of the pre-tokenizer pattern is encoded by itself. The leaves of a segment tree are the byte positions of the
match; a live position's leaf holds the rank of the pair that starts there (none: infinity), inner nodes the smaller
child, the left one on ties, so the root is the leftmost lowest pair. A merge writes three leaves (the merged pair, its
left neighbour and the absorbed one) and the paths above them: O(log n) each. Short matches that a batch has not met
yet are encoded together, one tree per row of a matrix, step by step; long ones have a tree of their own. Results
are kept by match in a bounded store.

Defined results: a null text is empty and has no ids; texts are encoded whole; repeated rows give repeated results; an empty
table gives none; other columns may have any name.
"""

from __future__ import annotations

import base64
import hashlib
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import boxed, sliced_texts, table, trimmed, unboxed

NONE = np.int64(1 << 40)
#: Matches up to this many bytes are encoded side by side; the store keeps so many matches.
SHORT, STORE = 64, 150_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def default_ranks_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


class Encoder:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.tokens = {i: b for b, i in ranks.items()}
        self.pattern = regex.compile(pattern)
        self.bytes_id = np.array([ranks[bytes([b])] for b in range(256)], np.int64)
        pairs: dict[int, int] = {}
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    pairs[left << 20 | right] = rank
        self.pairs = pairs
        self.keys = np.array(sorted(pairs), np.int64)
        self.values = np.array([pairs[k] for k in self.keys.tolist()], np.int64)
        self.decimal = {i: str(i) for i in self.tokens}
        self.store: dict[str, tuple[int, str, bytes]] = {}
        self.chunks: dict[str, tuple[int, str, bytes]] = {}
        self.old_store: dict[str, tuple[int, str, bytes]] = {}
        self.old_chunks: dict[str, tuple[int, str, bytes]] = {}

    def pair_ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair, NONE where the pair is no token or a side is missing (-1)."""
        key = left << 20 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((left >= 0) & (right >= 0) & (self.keys[at] == key), self.values[at], NONE)

    def long_match(self, raw: bytes) -> list[int]:
        """One tree for one match."""
        n = len(raw)
        ids = self.bytes_id[np.frombuffer(raw, np.uint8)].tolist()
        size = 1 << max(1, (n - 1).bit_length())
        none, get = int(NONE), self.pairs.get
        tree = [none] * (2 * size)
        for i in range(n - 1):
            tree[size + i] = get(ids[i] << 20 | ids[i + 1], none)
        for i in range(size - 1, 0, -1):
            tree[i] = min(tree[2 * i], tree[2 * i + 1])
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))

        def put(leaf: int, value: int) -> None:
            i = size + leaf
            tree[i] = value
            i >>= 1
            while i:
                least = tree[2 * i] if tree[2 * i] <= tree[2 * i + 1] else tree[2 * i + 1]
                if tree[i] == least:
                    break
                tree[i] = least
                i >>= 1

        while tree[1] < none:
            i = 1
            while i < size:
                i = 2 * i if tree[2 * i] <= tree[2 * i + 1] else 2 * i + 1
            i -= size
            gone = after[i]
            ids[i] = tree[1]
            after[i] = after[gone]
            ids[gone] = -1
            put(gone, none)
            if after[i] < n:
                before[after[i]] = i
                put(i, get(ids[i] << 20 | ids[after[i]], none))
            else:
                put(i, none)
            if before[i] >= 0:
                put(before[i], get(ids[before[i]] << 20 | ids[i], none))
        return [x for x in ids if x >= 0]

    def short_matches(self, raws: list[bytes], size: int) -> tuple[np.ndarray, np.ndarray]:
        """A tree per row, all rows a merge further at each step; `size` (a power of two) bounds their bytes.

        Returns the ids of all rows, one after the other, and how many each has. Matrices are kept flat: leaf i of row r is at
        r * 2 * size + size + i of the trees and at r * (size + 2) + i of the links, whose last two places stand for no neighbour.
        """
        m, wide = len(raws), size + 2
        raw = np.frombuffer(b"".join([r.ljust(size, b"\0") for r in raws]), np.uint8).reshape(m, size)
        lengths = np.fromiter(map(len, raws), np.int64, m)
        ids = np.full((m, wide), -1, np.int64)
        ids[:, :size] = np.where(np.arange(size) < lengths[:, None], self.bytes_id[raw], -1)
        # A node holds rank * size + position, so the smaller value is also the leftmost of equal ranks.
        empty = NONE * size
        tree = np.full((m, 2 * size), empty, np.int64)
        ranks = self.pair_ranks(ids[:, :size], ids[:, 1 : size + 1])
        tree[:, size:] = np.where(ranks < NONE, ranks * size + np.arange(size), empty)
        level = size
        while level > 1:
            np.minimum(tree[:, level : 2 * level : 2], tree[:, level + 1 : 2 * level : 2], out=tree[:, level // 2 : level])
            level //= 2
        after = np.tile(np.arange(1, wide + 1), m)
        before = np.tile(np.arange(-1, wide - 1), m)
        tree, ids, depth = tree.ravel(), ids.ravel(), size.bit_length() - 1

        def put(roots: np.ndarray, leaf: np.ndarray, rank: np.ndarray) -> None:
            node = leaf + size
            tree[roots + node] = np.where(rank < NONE, rank * size + leaf, empty)
            for _ in range(depth):
                child = roots + (node | 1)
                node >>= 1
                tree[roots + node] = np.minimum(tree.take(child), tree.take(child - 1))

        rows = np.flatnonzero(tree[1 :: 2 * size] < empty)
        while len(rows):
            roots, links = rows * (2 * size), rows * wide
            top = tree.take(roots + 1)
            at = top % size
            here = links + at
            gone = after.take(here)
            merged = top // size
            ids[here], ids[links + gone] = merged, -1
            following = np.minimum(after.take(links + gone), size)
            after[here] = following
            before[links + following] = at
            left = before.take(here)
            right_id, has = ids.take(links + following), np.flatnonzero(left >= 0)
            put(roots, gone, np.full(len(rows), NONE))
            put(roots, at, self.pair_ranks(merged, right_id))
            if len(has):
                put(roots[has], left[has], self.pair_ranks(ids.take(links[has] + left[has]), merged[has]))
            rows = rows[tree.take(roots + 1) < empty]
        body = ids.reshape(m, wide)[:, :size]
        live = body >= 0
        return body[live], live.sum(1)

    def learn(self, matches: set[str]) -> None:
        """Put the results of unseen matches in the store."""
        by_size: dict[int, list[tuple[str, bytes]]] = {}
        for match in matches:
            raw = match.encode()
            if (whole := self.ranks.get(raw)) is not None:
                self.store[match] = (1, self.decimal[whole], raw)
            elif len(raw) <= SHORT:
                by_size.setdefault(max(2, 1 << (len(raw) - 1).bit_length()), []).append((match, raw))
            else:
                self._keep(match, self.long_match(raw))
        for size, items in by_size.items():
            for start in range(0, len(items), 4096):
                part = items[start : start + 4096]
                ids, counts = self.short_matches([raw for _, raw in part], size)
                ids, stop = ids.tolist(), 0
                for (match, _), n in zip(part, counts.tolist(), strict=True):
                    self._keep(match, ids[stop : stop + n])
                    stop += n

    def _keep(self, match: str, ids: list[int]) -> None:
        self.store[match] = (len(ids), ",".join([self.decimal[i] for i in ids]), b"".join([self.tokens[i] for i in ids]))

    def _need(self, store: dict, old: dict, wanted: set) -> set:
        """What is in neither generation of a store; what the old one has moves over."""
        missing = wanted - store.keys()
        kept = missing & old.keys()
        store.update((k, old[k]) for k in kept)
        return missing - kept

    def results(self, texts: list[str]) -> Iterator[list[tuple[int, str, bytes]]]:
        """For each text the results of its chunks: count of ids, ids in decimal joined by commas, decoded bytes.

        Between characters that are not white space, a single blank always begins a match and a single line end is one,
        so texts whose only white space is such are cut there first, and results are kept by chunk; the pattern then runs
        once for each distinct chunk. Other texts go through the pattern whole.
        """
        cut: list[list[str] | None] = []
        for text in texts:
            lines = text.split("\n")
            chunks, first = [], True
            for line in lines:
                words = line.split(" ")
                if not first:
                    chunks.append("\n")
                chunks.append(words[0])
                chunks += [" " + w for w in words[1:]]
                first = False
            clean = text and len(text.split()) == len(chunks) - len(lines) + 1
            cut.append(chunks if clean else self.pattern.findall(text))
        if len(self.chunks) > STORE:
            self.old_chunks, self.chunks = self.chunks, {}
        new = self._need(self.chunks, self.old_chunks, set().union(*cut))
        parts = {c: self.pattern.findall(c) for c in new}
        if len(self.store) > STORE:
            self.old_store, self.store = self.store, {}
        self.learn(self._need(self.store, self.old_store, set().union(*parts.values())))
        for chunk, found in parts.items():
            got = [self.store[m] for m in found]
            self.chunks[chunk] = got[0] if len(got) == 1 else (sum([g[0] for g in got]), ",".join([g[1] for g in got]), b"".join([g[2] for g in got]))
        for chunks in cut:
            yield [self.chunks[c] for c in chunks]

    def forget(self) -> None:
        """Drop stored results: a worker that serves other kernels next must not keep them."""
        for store in (self.store, self.chunks, self.old_store, self.old_chunks):
            store.clear()

    def encode(self, text: str | None) -> list[int]:
        (got,) = self.results([text or ""])
        return [int(x) for g in got for x in g[1].split(",")]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


#: The encoder of a worker process.
_ENCODERS: dict[str, Encoder] = {}


class Ranks:
    """Ranks as broadcast to the executors, which need no file of their own: the driver reads it once."""

    def __init__(self, spark: SparkSession, path: str | None):
        import public_tokenizers

        data = pickle.dumps(read_ranks(path or default_ranks_path()))
        self.pattern, self.name = public_tokenizers.PATTERN, hashlib.sha256(data).hexdigest()
        self.shared = spark.sparkContext.broadcast(data)

    def encoder(self) -> Encoder:
        if self.name not in _ENCODERS:
            _ENCODERS.clear()
            _ENCODERS[self.name] = Encoder(pickle.loads(self.shared.value), self.pattern)
        return _ENCODERS[self.name]


def encoded(docs: DataFrame, keep: list[str], path: str | None = None, ids: bool = False, text_col: str = "text") -> DataFrame:
    """The kept columns, n_tokens, ids_sha256, decoded_sha256 and, if asked, the ids: one scan, no shuffle."""
    ranks = Ranks(docs.sparkSession, path)
    names = ["n_tokens", "ids_sha256", "decoded_sha256", "ids"][: 4 if ids else 3]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ranks.encoder()
        for batch in sliced_texts(batches, "text"):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            rows = []
            for got in encoder.results(texts):
                line = ",".join([g[1] for g in got])
                row = [sum([g[0] for g in got]), hashlib.sha256(line.encode()).hexdigest(), hashlib.sha256(b"".join([g[2] for g in got])).hexdigest()]
                rows.append([*row, [int(x) for x in line.split(",")] if ids and line else []])
            columns = list(zip(*rows, strict=True))[: len(names)]
            yield pa.RecordBatch.from_arrays([batch.column("row"), *(pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.string(), pa.string(), pa.list_(pa.int32())), strict=False))], ["row", *names])
        encoder.forget()

    chosen = boxed(docs, keep, text_col)
    schema = chosen.select("row").schema.add("n_tokens", "long").add("ids_sha256", "string").add("decoded_sha256", "string")
    return unboxed(chosen.mapInArrow(lambda batches: trimmed(run(batches)), schema.add("ids", T.ArrayType(T.IntegerType())) if ids else schema), *names)


def decoded(tokens: DataFrame, keep: list[str], path: str | None = None, ids_col: str = "ids") -> DataFrame:
    """The kept columns and the text that the ids stand for (invalid UTF-8 is replaced)."""
    ranks = Ranks(tokens.sparkSession, path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ranks.encoder()
        for batch in batches:
            texts = pa.array([encoder.decode(x or []).decode("utf-8", "replace") for x in batch.column("ids").to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("row"), texts], ["row", "text"])

    chosen = tokens.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"), F.col(ids_col).alias("ids"))
    return unboxed(chosen.mapInArrow(run, chosen.select("row").schema.add("text", "string")), "text")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoded(table(spark, sf_dir, "documents"), ["doc_id"])
