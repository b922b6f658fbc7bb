"""The forest join against brute force over all pairs."""

import pytest

from multiway.llm.common import WordHashes
from multiway.llm.neardup import CROWD, TREES, Forest, _linked, components, cut_nodes, floor_depth, gain, keep_one, near_duplicates, needed, shingles, verify_node

SCHEMA = "doc_id long, text string, lang string, n_links int"


def brute(rows, threshold=0.8):
    hashes = WordHashes()
    texts = sorted({t for _, t in rows if t is not None})
    sets = {t: frozenset(shingles(t, hashes).tolist()) for t in texts}
    near = {t: set() for t in texts}
    for i, a in enumerate(texts):
        for b in texts[i + 1 :]:
            both = len(sets[a] & sets[b])
            if both and both >= threshold * (len(sets[a]) + len(sets[b]) - both):
                near[a].add(b)
                near[b].add(a)
    ids = {}
    for t in texts:
        seen, todo = {t}, [t]
        while todo:
            for u in near[todo.pop()] - seen:
                seen.add(u)
                todo.append(u)
        own = [d for d, u in rows if u in seen and d is not None]
        ids[t] = min(own) if own else None
    return sorted((d, d if t is None else ids[t], 0 if t is None else len(near[t])) for d, t in rows if d is not None)


def rows_of(df):
    return sorted((r["doc_id"], r["class_id"], r["n_links"]) for r in df.collect() if r["doc_id"] is not None)


def edited(words, at):
    return " ".join(w if i not in at else f"x{i}" for i, w in enumerate(words))


def test_small_cases(spark):
    base = [f"w{i}" for i in range(200)]
    rows = [(1, " ".join(base)), (2, " ".join(base)), (3, edited(base, {5})), (4, edited(base, {50, 150})), (5, ""), (6, ""), (7, None), (8, "one two"), (9, "One, two!"), (10, "!!! ..."), (11, " ".join(base[:100])), (None, " ".join(base)), (12, " ".join(["a b c d e f"] * 30_000)), (3, edited(base, {5}))]
    docs = spark.createDataFrame([(d, t, "en", 1) for d, t in rows], SCHEMA)
    assert rows_of(near_duplicates(docs)) == brute(rows)
    kept = keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] or 0 for r in kept.collect()) == [1, 5, 7, 8, 10, 11, 12]


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert rows_of(near_duplicates(docs)) == brute([(r["doc_id"], r["text"]) for r in docs.collect()])


def test_blocks_split_a_hot_node(spark):
    base = [f"w{i}" for i in range(120)]
    rows = [(i, edited(base, {i % 100})) for i in range(150)] + [(1000 + i, f"alone {i} " + " ".join(f"q{i}{j}" for j in range(30))) for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert rows_of(near_duplicates(docs, block=16)) == brute(rows)


def test_empty_table(spark):
    assert near_duplicates(spark.createDataFrame([], SCHEMA)).count() == 0


def test_floor_lies_below_what_a_uniform_cut_needs():
    for trees, target in ((20, 0.9995), (20, 0.9), (6, 0.9995)):
        d = floor_depth(0.8, trees, 8, target)
        assert d == 1 or 1 - (1 - 0.8 ** (d + 1)) ** trees >= target
        assert d >= 7 or 1 - (1 - 0.8 ** (d + 2)) ** trees < target


def labelled(spark, sets, forest):
    rows = [(i.to_bytes(4, "big"), forest.labels(s), len(s)) for i, s in enumerate(sets)]
    return spark.createDataFrame(rows, "key binary, labels binary, size int")


def test_prefixes_are_short_where_it_is_easy_and_long_where_it_is_crowded(spark):
    import numpy as np

    random, forest = np.random.default_rng(3), Forest()
    pool = [random.integers(0, 1 << 62, 150).astype(np.uint64) for _ in range(30)]
    easy = [np.unique(np.concatenate([p[: 140 + k], p[145:]])) for p in pool for k in (0, 5)]
    core = random.integers(0, 1 << 62, 150).astype(np.uint64)
    crowded = [np.unique(np.concatenate([np.delete(core, random.choice(150, 8, replace=False)), random.integers(0, 1 << 62, 8).astype(np.uint64)])) for _ in range(400)]
    depth = {}
    for name, sets in (("easy", easy), ("crowded", crowded)):
        rows = cut_nodes(labelled(spark, sets, forest), forest, CROWD).collect()
        depth[name] = [r["depth"] for r in rows]
        by_key = {}
        for r in rows:
            by_key.setdefault(bytes(r["key"]), []).append(r["depth"])
        for depths in by_key.values():  # every text reaches the target over all trees
            assert sum(gain(d, 0.8) for d in depths) + (TREES - len(depths)) * gain(forest.floor, 0.8) >= needed(forest.target) - 1e-9
    assert set(depth["easy"]) == {forest.floor}
    assert np.mean(depth["crowded"]) > forest.floor + 0.5 and max(depth["crowded"]) > forest.floor


def test_recall_at_the_threshold(spark):
    """Pairs of exactly or little more than the threshold, in a crowd of their like: recall against all pairs."""
    import numpy as np

    random = np.random.default_rng(5)
    rows = []
    for g in range(40):
        base = [f"g{g}w{k}" for k in range(204)]
        for k in range(12):  # each edit of one word takes five shingles away
            rows.append((100 * g + k, edited(base, set(random.choice(np.arange(5, 199, 6), 2, replace=False).tolist()))))
    want = {d: n for d, _, n in brute(rows)}
    for crowd in (CROWD, 2):
        got = {r["doc_id"]: r["n_links"] for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), crowd=crowd).collect()}
        assert all(got[d] <= want[d] for d in want)
        recall = sum(got.values()) / sum(want.values())
        print("links", sum(want.values()) // 2, "crowd", crowd, "recall", recall)
        assert recall >= 0.999


def test_repeats_clashes_and_missing_ids_keep_one_row(spark):
    base = " ".join(f"w{i}" for i in range(60))
    rows = [(d, t, k, "x", b"n", 1) for k in range(3) for d, t in ((1, base), (2, base + " end"), (3, "another text of its own kind here"), (None, "no id has this text at all"), (None, base), (None, None), (4, ""))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, key int, row string, packed binary, n_links int")
    kept = keep_one(docs)
    assert kept.columns == docs.columns
    got = sorted((r["doc_id"] or 0, r["text"] or "", r["key"]) for r in kept.collect())
    assert got == sorted([(1, base, 0), (3, "another text of its own kind here", 0), (0, "no id has this text at all", 0), (0, "", 0), (0, "", 1), (0, "", 2), (4, "", 0)])
    mapped = spark.createDataFrame([(1, base, {"a": 1}), (1, base, {"a": 2})], "doc_id long, text string, m map<string,int>")
    assert keep_one(mapped).count() == 1
    assert keep_one(docs.limit(0)).count() == 0


def test_a_node_is_verified_alike_in_squares():
    import numpy as np

    random = np.random.default_rng(1)
    core = random.integers(0, 1 << 60, 80).astype(np.uint64)
    sets = [np.unique(np.concatenate([core[: 60 + i % 20], random.integers(0, 1 << 60, 6).astype(np.uint64)])) for i in range(50)]
    keys, met = [bytes([i]) for i in range(50)], np.full((50, 2), 7)
    one = [verify_node(keys, met, sets, np.arange(50) % 2, a, b, 7, 0.8, square) for square in (512, 8) for a, b in ((0, 0), (0, 1), (1, 1))]
    assert [[(k, n) for k, _, n in part] for part in one[:3]] == [[(k, n) for k, _, n in part] for part in one[3:]]
    assert sum(n for part in one[:3] for _, _, n in part) == 2 * sum(_linked([sets[i]], [sets[j]], False, 0.8)[0, 0] for i in range(50) for j in range(i))


@pytest.mark.parametrize("same", [True, False])
def test_both_ways_of_verifying_agree(same):
    import numpy as np

    random = np.random.default_rng(0)
    pool = random.integers(0, 1 << 60, 300).astype(np.uint64)
    sets = [np.unique(random.choice(pool[: 60 + 5 * (i % 3)], 55, replace=False)) for i in range(24)]
    a, b = (sets, sets) if same else (sets[:10], sets[10:])
    got = _linked(a, b, same, 0.6)
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            both = len(np.intersect1d(x, y))
            assert got[i, j] == ((not same or i < j) and both >= 0.6 * (len(x) + len(y) - both))


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(f"{i:03}".encode(), f"{i + 1:03}".encode()) for i in range(40)] + [(b"900", b"901")], "u binary, v binary")
    got = {bytes(r["vertex"]): bytes(r["root"]) for r in components(edges).collect()}
    assert got == {f"{i:03}".encode(): b"000" for i in range(1, 41)} | {b"901": b"900"}


def test_components_of_hubs_and_long_chains(spark):
    hub = [(f"h{i:05}".encode(), b"a0") for i in range(3000)]
    chain = [(f"c{(i * 7919) % 301:04}".encode(), f"c{((i + 1) * 7919) % 301:04}".encode()) for i in range(300)]
    got = {bytes(r["vertex"]): bytes(r["root"]) for r in components(spark.createDataFrame([*hub, *chain, (b"h00001", b"c0003")], "u binary, v binary")).collect()}
    assert set(got.values()) == {b"a0"} and len(got) == 3301
