"""N-gram Jaccard join with a MinHash LSH forest and exact verification.

Equal texts form a class, known by the MD5 of the text; one text of each class goes on. A text is the set of its
five-word shingles (words: small letters, punctuation dropped). In each of `TREES` tries it has a label, its MinHash values in
order, as bytes: sorted labels are the trie. Texts that are in the same cut node of a trie are candidates, and the cut
of a trie is found from the longest prefixes upwards:

* a prefix of `LEVELS` values is shortened as long as the shorter node holds no more than `crowd` texts, down to the floor;
* a text whose cuts, over all trees, don't yet give a pair at the threshold the target probability of meeting has more of
  its prefixes shortened to the floor until they do, those in the most crowded nodes first: a tree in which a text stands
  apart from its like is the one in which its pairs don't meet, so the other order would promise more than it keeps.

So sparse regions are matched by short prefixes, crowded ones by long prefixes in as many trees as the target allows. A node's
texts share its cut, so both texts of a pair agree on where they meet. The floor is one value shorter than the prefix at which
all trees alike would just reach the target.

Within a node all pairs are verified on their shingle sets, and a pair counts only in the first tree in which it meets, so
links are counted once although no pair is ever written: a node yields for each text its number of links and one text of its
linked component. A node beyond a block's rows or shingles is cut into blocks, and two blocks meet in a task; a text then
travels once for each block of its node: up to 8 times, and n / 4096 times in a node of n > 32,768 texts. Components over nodes come from
hooking every text to its least neighbour, jumping to the roots and contracting, until no edge is left.

Defined results: texts without words are only similar to equal texts; a null text is alone; texts of one to four words are one
shingle; rows that repeat an id or a text are each returned; a class is named by its smallest id (null if it has
none); an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import WordHashes, discard, lookup, sliced_texts, stored, table, trimmed, window_hashes
from .decontaminate import words_of

SHINGLE, THRESHOLD = 5, 0.8
TREES, LEVELS, TARGET_RECALL = 20, 8, 0.9995
#: Texts that a node may hold while its prefix is shortened without need.
CROWD = 64
#: Texts of a block, two of which meet in one task; a node is first cut into up to so many small blocks, for tasks of its own,
#: and beyond that into large ones, for few copies of a text. Shingles that a block may hold.
SMALL_BLOCK, SMALL_BLOCKS, BLOCK, BLOCK_SHINGLES = 512, 8, 4096, 2_000_000
#: Pairs are compared in squares of so many texts.
SQUARE = 512


def gain(depth: int, threshold: float) -> float:
    """What one tree adds to -log(probability of missing a pair at the threshold) when prefixes of this length are matched."""
    return -math.log1p(-(threshold**depth))


def needed(target: float) -> float:
    return -math.log1p(-target)


def floor_depth(threshold: float = THRESHOLD, trees: int = TREES, levels: int = LEVELS, target: float = TARGET_RECALL) -> int:
    """One value less than the longest prefix at which all trees alike reach the target, so that some may stay longer."""
    return max(1, next((d for d in range(levels, 0, -1) if trees * gain(d, threshold) >= needed(target)), 1) - 1)


def shingles(text: str | None, hashes: WordHashes, width: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit shingles."""
    text = text or ""
    words = words_of(text if text.isascii() else text.lower())
    if not words:
        return np.empty(0, np.uint64)
    return np.unique(window_hashes(hashes.of(words), min(width, len(words))))


class Forest:
    def __init__(self, trees: int = TREES, levels: int = LEVELS, threshold: float = THRESHOLD, target: float = TARGET_RECALL, seed: int = 11):
        random = np.random.default_rng(seed)
        self.trees, self.levels, self.threshold, self.target = trees, levels, threshold, target
        self.floor = floor_depth(threshold, trees, levels, target)
        self.factor = random.integers(0, 1 << 32, trees * levels, dtype=np.uint32) | np.uint32(1)
        self.shift = random.integers(0, 1 << 32, trees * levels, dtype=np.uint32)

    @property
    def label_bytes(self) -> int:
        """Eight bytes for tree and floor prefix, two for each value below it."""
        return 8 + 2 * (self.levels - self.floor)

    def labels(self, shingle_set: np.ndarray) -> bytes:
        """The labels of all trees, one after the other."""
        x = (shingle_set ^ (shingle_set >> np.uint64(32))).astype(np.uint32)
        least = np.full(len(self.factor), 0xFFFFFFFF, np.uint32)
        for start in range(0, len(x), 1024):
            values = x[None, start : start + 1024] * self.factor[:, None]
            values += self.shift[:, None]
            np.minimum(least, values.min(1), out=least)
        values = least.reshape(self.trees, self.levels)
        key = np.arange(1, self.trees + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for level in range(self.floor):
            key = (key ^ values[:, level]) * np.uint64(0xD6E8FEB86659FD93)
            key ^= key >> np.uint64(32)
        below = ((values[:, self.floor :] * np.uint32(0x85EBCA6B)) >> np.uint32(16)).astype(np.uint16)
        return np.hstack([key[:, None].view(np.uint8), np.ascontiguousarray(below).view(np.uint8)]).tobytes()

    def prefix(self, depth: str = "depth", label: str = "label"):
        """The label's prefix of a length in MinHash values, in SQL; as bytes it names the node."""
        return F.expr(f"substring({label}, 1, 8 + 2 * ({depth} - {self.floor}))")

    def gains(self, depth: str = "depth"):
        return F.element_at(F.array(*[F.lit(gain(d, self.threshold)) for d in range(1, self.levels + 1)]), F.col(depth))


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).alias("doc_id"), F.unhex(F.md5(text.cast("binary"))).alias("key"), text.alias("text"))


def _with_labels(keyed: DataFrame, forest: Forest, width: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in sliced_texts(batches, "text"):
            labels, sizes = [], []
            for text in batch.column("text").to_pylist():
                s = shingles(text, hashes, width)
                labels.append(forest.labels(s) if len(s) else None)
                sizes.append(len(s))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("key"), pa.array(labels, pa.binary()), pa.array(sizes, pa.int32())], ["doc_id", "key", "labels", "size"])

    return keyed.mapInArrow(lambda batches: trimmed(run(batches)), keyed.select("doc_id", "key").schema.add("labels", "binary").add("size", T.IntegerType()))


def cut_nodes(classes: DataFrame, forest: Forest, crowd: int = CROWD) -> DataFrame:
    """key, size, tree, node, depth of texts that share a floor node with another: the cut of each trie, as chosen above.

    Counts are taken by aggregation on prefixes and come back by lookup(), so a node may hold any share of the texts.
    """
    floor, width = forest.floor, forest.label_bytes
    at = F.explode(F.sequence(F.lit(0), F.lit(forest.trees - 1)))
    places = classes.filter("labels IS NOT NULL").select("key", "size", "labels", at.alias("tree")).select("key", "size", "tree", F.expr(f"substring(labels, tree * {width} + 1, {width})").alias("label")).withColumn("root", F.expr("substring(label, 1, 8)"))
    shared = stored(places.groupBy("root").agg(F.count("*").alias("n")).filter("n > 1"))
    members = stored(lookup(places, shared, "root", "inner"))
    crowded = members.filter(F.col("n") > crowd)
    if crowded.isEmpty():
        return members.select("key", "size", "tree", F.col("root").alias("node"), F.lit(floor).alias("depth"))
    # From the longest prefix up: the cut lies below the last prefix that is too crowded.
    below = crowded.select("key", "tree", "label", F.explode(F.sequence(F.lit(floor + 1), F.lit(forest.levels))).alias("depth")).withColumn("node", forest.prefix())
    full = stored(below.groupBy("node").agg(F.count("*").alias("n")).filter(F.col("n") > crowd).select("node"))
    deepest = lookup(below.select("key", "tree", "depth", "node"), full, "node", "inner").groupBy("key", "tree").agg(F.max("depth").alias("_full"))
    depth = F.when(F.col("n") <= crowd, floor).otherwise(F.least(F.lit(forest.levels), F.coalesce("_full", F.lit(floor)) + 1))
    cut = stored(members.join(deepest, ["key", "tree"], "left").withColumn("depth", depth.cast("int")).drop("_full"))
    # Texts short of the target: trees are opened at the floor, the most crowded first. A tree without company is at the floor.
    own = Window.partitionBy("key")
    lacking = F.lit(needed(forest.target)) - F.sum(forest.gains() - F.lit(gain(floor, forest.threshold))).over(own) - F.lit(forest.trees * gain(floor, forest.threshold))
    more = F.lit(gain(floor, forest.threshold)) - forest.gains()
    before = F.sum(more).over(own.orderBy(F.desc("n"), "tree").rowsBetween(Window.unboundedPreceding, -1))
    opened = cut.withColumn("_lacking", lacking).withColumn("_before", F.coalesce(before, F.lit(0.0))).filter(f"depth > {floor} AND _lacking > _before").select("root").distinct().withColumn("_open", F.lit(True))
    final = lookup(cut, stored(opened), "root").withColumn("depth", F.when(F.col("_open"), floor).otherwise(F.col("depth")))
    return final.select("key", "size", "tree", forest.prefix().alias("node"), "depth")


def candidate_members(classes: DataFrame, forest: Forest, crowd: int = CROWD, block: int = BLOCK) -> DataFrame:
    """node, blocks, key, met (for each tree the node a text is in): texts of nodes of two or more; nodes with the same texts are one."""
    cut = stored(cut_nodes(classes, forest, crowd))
    nodes = cut.groupBy("node").agg(F.count("*").alias("n"), F.sum("size").alias("weight"), F.min("tree").alias("tree"), F.bit_xor(F.xxhash64("key")).alias("x"), F.bit_xor(F.xxhash64("key", F.lit(1))).alias("y")).filter("n > 1")
    small = F.least(F.ceil(F.col("n") / min(SMALL_BLOCK, block)), F.lit(SMALL_BLOCKS))
    blocks = F.greatest(small, F.ceil(F.col("n") / block), F.ceil(F.col("weight") / BLOCK_SHINGLES)).cast("int")
    kept = stored(nodes.groupBy("n", "weight", "x", "y").agg(F.min(F.struct("tree", "node")).alias("first")).select(F.col("first.node").alias("node"), blocks.alias("blocks")))
    places = F.map_from_entries(F.collect_list(F.struct("tree", F.xxhash64("node"))))
    met = cut.groupBy("key").agg(places.alias("_at")).select("key", F.transform(F.sequence(F.lit(0), F.lit(forest.trees - 1)), lambda t: F.coalesce(F.try_element_at("_at", t), F.xxhash64("key", t, F.lit("alone")))).alias("met"))
    return lookup(cut.select("node", "key"), kept, "node", "inner").select(F.xxhash64("node").alias("node"), "blocks", "key").join(met, "key")


def _parts(members: DataFrame) -> DataFrame:
    """One row for each pair of blocks that a text takes part in; a node of one block is one part."""
    own = F.pmod(F.xxhash64("key", F.lit(2)), F.col("blocks")).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    return members.withColumn("_own", own).withColumn("_other", other).withColumn("_a", F.least("_own", "_other")).withColumn("_b", F.greatest("_own", "_other"))


def _linked(a: list[np.ndarray], b: list[np.ndarray], same: bool, threshold: float) -> np.ndarray:
    """Which pairs of two lists of shingle sets reach the threshold (for one list with itself: above the diagonal)."""
    na, nb = np.array([len(x) for x in a]), np.array([len(x) for x in b])
    possible = np.minimum(na[:, None], nb[None]) >= threshold * np.maximum(na[:, None], nb[None])
    if same:
        possible &= np.arange(len(a))[:, None] < np.arange(len(b))[None]
    where = np.argwhere(possible)
    out = np.zeros(possible.shape, bool)
    if len(where) <= 64:
        for i, j in where:
            both = len(np.intersect1d(a[i], b[j], assume_unique=True))
            out[i, j] = both >= threshold * (na[i] + nb[j] - both)
        return out
    sets = a if same else [*a, *b]
    flat = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    values, number, count = np.unique(flat, return_inverse=True, return_counts=True)
    shared = count > 1
    renumber = np.cumsum(shared) - 1
    keep = shared[number]
    number, owner = renumber[number[keep]], owner[keep]
    order = np.argsort(number, kind="stable")
    number, owner = number[order], owner[order]
    both = np.zeros(possible.shape, np.float32)
    for start in range(0, int(shared.sum()), 4096):
        lo, hi = np.searchsorted(number, (start, start + 4096))
        dense = np.zeros((len(sets), 4096), np.float32)
        dense[owner[lo:hi], number[lo:hi] - start] = 1
        both += dense @ dense.T if same else dense[: len(a)] @ dense[len(a) :].T
    return possible & (both >= threshold * (na[:, None] + nb[None] - both) - 1e-3)


def _unite(root: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Roots after linking i and j, each the least place of its component."""
    while True:
        a, b = root[i], root[j]
        if (a == b).all():
            return root
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while not (root[root] == root).all():
            root = root[root]


def verify_node(keys: list[bytes], met: np.ndarray, sets: list[np.ndarray], blocks: np.ndarray, a: int, b: int, node: int, threshold: float, square: int = SQUARE) -> list[tuple[bytes, bytes, int]]:
    """(key, a key of its component, links) of each text with a link that this part counts; square by square."""
    left = np.flatnonzero(blocks == a)
    right = left if a == b else np.flatnonzero(blocks == b)
    if len(left) < (2 if a == b else 1) or not len(right):
        return []
    # Texts of much the same size stand together, so squares of texts too different in size are skipped.
    sizes = np.array([len(s) for s in sets])
    left, right = left[np.argsort(sizes[left], kind="stable")], right[np.argsort(sizes[right], kind="stable")]
    degree, root = np.zeros(len(keys), np.int64), np.arange(len(keys))
    for x in range(0, len(left), square):
        own = left[x : x + square]
        for y in range(x if a == b else 0, len(right), square):
            other = right[y : y + square]
            if sizes[own[-1]] < threshold * sizes[other[0]] or sizes[other[-1]] < threshold * sizes[own[0]]:
                continue
            i, j = np.nonzero(_linked([sets[k] for k in own], [sets[k] for k in other], a == b and x == y, threshold))
            i, j = own[i], other[j]
            first = (met[i] == met[j]).argmax(1)
            mine = met[i, first] == node
            i, j = i[mine], j[mine]
            if len(i):
                degree += np.bincount(i, minlength=len(keys)) + np.bincount(j, minlength=len(keys))
                root = _unite(root, i, j)
    return [(keys[k], keys[root[k]], int(degree[k])) for k in np.flatnonzero(degree)]


def verified(parts: DataFrame, threshold: float, width: int) -> DataFrame:
    """key, other, links from parts with node, blocks, _a, _b, _own, key, met, packed."""
    import zstandard

    columns = ["node", "_a", "_b", "_own", "key", "met", "packed"]
    sorted_parts = parts.select(*columns).repartition("node", "_a", "_b").sortWithinPartitions("node", "_a", "_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, large, at, held, out = WordHashes(), zstandard.ZstdDecompressor(), None, [], []

        def finish() -> None:
            if len(held) > 1:
                own, keys, met, sets = zip(*held, strict=True)
                out.extend(verify_node(list(keys), np.stack(met), list(sets), np.array(own), at[1], at[2], at[0], threshold))

        def flush() -> pa.RecordBatch:
            keys, others, links = zip(*out, strict=True) if out else ((), (), ())
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(others, pa.binary()), pa.array(links, pa.int64())], ["key", "other", "links"])

        for batch in batches:
            for row in zip(*(batch.column(c) for c in columns), strict=True):
                node, a, b, own, key, met, packed = (x.as_py() for x in row)
                if (node, a, b) != at:
                    finish()
                    at, held = (node, a, b), []
                held.append((own, key, np.array(met, np.int64), shingles(large.decompress(packed).decode(), hashes, width)))
            if len(out) > 20_000:
                yield flush()
        finish()
        yield flush()

    return sorted_parts.mapInArrow(lambda batches: trimmed(run(batches)), "key binary, other binary, links long")


def packed_texts(keyed: DataFrame) -> DataFrame:
    """key and the compressed text."""
    import zstandard

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        small = zstandard.ZstdCompressor(1)
        for batch in sliced_texts(batches, "text"):
            texts = pa.array([small.compress(t.encode()) for t in batch.column("text").to_pylist()], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("key"), texts], ["key", "packed"])

    return keyed.filter("key IS NOT NULL").select("key", "text").mapInArrow(run, "key binary, packed binary")


def components(edges: DataFrame) -> DataFrame:
    """(vertex, root) for every vertex of an edge but the roots; a root is the least vertex of its component.

    Each round hooks a vertex to its least neighbour, jumps along hooks to their roots and keeps the edges between roots. It
    ends when there are none, and every round takes away all vertices that have a smaller neighbour.
    """
    oriented = lambda df: df.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    edges, found = stored(oriented(edges.select("u", "v"))), []
    while not edges.isEmpty():
        hook = stored(edges.groupBy("u").agg(F.min("v").alias("p")))
        while True:
            jumped = stored(lookup(hook, hook.select(F.col("u").alias("p"), F.col("p").alias("q")), "p"))
            if jumped.filter("q IS NOT NULL").isEmpty():
                discard(jumped)
                break
            before, hook = hook, stored(jumped.select("u", F.coalesce("q", "p").alias("p")))
            discard(before), discard(jumped)
        found.append(hook)
        one = lookup(edges, hook.withColumnRenamed("p", "pu"), "u").select(F.col("pu").alias("u"), "v")
        both = lookup(one, hook.select(F.col("u").alias("v"), F.col("p").alias("pv")), "v").select("u", F.coalesce("pv", "v").alias("v"))
        before, edges = edges, stored(oriented(both))
        discard(before)
    if not found:
        return edges.select(F.col("u").alias("vertex"), F.col("v").alias("root"))
    out = found[-1]
    for hook in reversed(found[:-1]):
        later = out.select(F.col("u").alias("p"), F.col("p").alias("q"))
        out = stored(out.unionByName(lookup(hook, later, "p").select("u", F.coalesce("q", "p").alias("p"))))
    return out.select(F.col("u").alias("vertex"), F.col("p").alias("root"))


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, width: int = SHINGLE, trees: int = TREES, levels: int = LEVELS, target: float = TARGET_RECALL, crowd: int = CROWD, block: int = BLOCK, id_col: str = "doc_id", text_col: str = "text", with_key: bool = False) -> DataFrame:
    """doc_id, class_id, n_links (other texts that are linked), n_copies (rows with an equal text, itself too).

    with_key: also `key` (MD5 of the text) and `chosen`, the key of the text that stands for the class: that of its smallest id.
    """
    forest = Forest(trees, levels, threshold, target)
    keyed = _keyed(docs, id_col, text_col)
    rows = stored(_with_labels(keyed, forest, width))
    classes = stored(rows.filter("key IS NOT NULL").groupBy("key").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n_copies"), F.first("labels").alias("labels"), F.first("size").alias("size")))
    members = stored(candidate_members(classes, forest, crowd, block))
    wanted = members.select("key").distinct()
    found = packed_texts(keyed).groupBy("key").agg(F.first("packed").alias("packed")).join(wanted, "key")
    links = stored(verified(_parts(members.join(found, "key")), threshold, width))
    degree = links.groupBy("key").agg(F.sum("links").alias("n_links"))
    roots = components(links.select(F.col("key").alias("u"), F.col("other").alias("v")))
    named = classes.select("key", "rep", "n_copies").join(degree, "key", "left").join(roots, F.col("key") == F.col("vertex"), "left").select("key", "rep", "n_copies", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("root", "key").alias("root"))
    named = stored(named)
    # Texts without an id come last, so a class with any id is named by one.
    smallest = named.groupBy("root").agg(F.min(F.struct(F.col("rep").isNull(), "rep", "key")).alias("_s")).select("root", F.col("_s.rep").alias("class_id"), F.col("_s.key").alias("chosen"))
    by_key = stored(lookup(named, stored(smallest), "root").select("key", "class_id", "n_links", "n_copies", "chosen"))
    more = ["key", "chosen"] if with_key else []
    out = lookup(rows.filter("key IS NOT NULL").select("doc_id", "key"), by_key, "key").select("doc_id", "class_id", "n_links", "n_copies", *more)
    alone = rows.filter("key IS NULL").select("doc_id", F.col("doc_id").alias("class_id"), F.lit(0).cast("long").alias("n_links"), F.lit(1).cast("long").alias("n_copies"))
    return out.unionByName(alone, allowMissingColumns=True)


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each class, with all columns: one with the smallest id, and of rows with that id and text the least.

    A class without any id keeps one row of its least text; rows with a null text are classes of their own and all stay. Rows are
    put together by id and text before they are exchanged, so one row that makes up a third of the table is no hot key.
    """
    classes = near_duplicates(docs, with_key=True)
    chosen = classes.filter("key = chosen AND doc_id <=> class_id").select(F.col("doc_id").alias("_id"), F.col("key").alias("_key")).distinct()
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    keyed = docs.select(row.alias("row"), F.col("doc_id").alias("id"), F.unhex(F.md5(F.col("text").cast("string").cast("binary"))).alias("key"))
    one = keyed.filter("key IS NOT NULL").groupBy("id", "key").agg(F.min("row").alias("row") if _ordered(docs) else F.first("row").alias("row"))
    kept = one.join(chosen, (F.col("key") == F.col("_key")) & F.col("id").eqNullSafe(F.col("_id")), "left_semi").select("row")
    return kept.unionByName(keyed.filter("key IS NULL").select("row")).select(*[F.col("row")[c].alias(c) for c in docs.columns])


def _ordered(docs: DataFrame) -> bool:
    """Maps and variants have no order; of rows with equal id and text any one is then kept."""
    return not any(word in docs.schema.simpleString() for word in ("map<", "variant"))


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
