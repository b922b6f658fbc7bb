"""Each stage of the pipeline on its own input, and the whole."""

import corpus_pipeline as P
from multiway.llm.decontaminate import words_of


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in P.STAGES:
        before = {r["doc_id"]: r for r in docs.collect()}
        out = stage(spark, docs, sf).cache()
        after = out.collect()
        assert {r["doc_id"] for r in after} <= set(before), name
        if name != P.STAGES[-1][0]:
            assert out.columns == docs.columns
            docs = out
    assert 0 < len(after) < 200
    bench = [words_of(r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    windows = {tuple(w[i : i + 10]) for w in bench for i in range(max(1, len(w) - 9))}
    for r in before.values():
        w = words_of(r["text"])
        assert not any(tuple(w[i : i + 10]) in windows for i in range(len(w) - 9))
    assert sorted(map(tuple, after)) == sorted(map(tuple, P.run(spark, sf).collect()))


NAMES = ("n_words", "n_hit", "items", "hit_ranges", "_text", "_n_words", "_mw_score", "score", "_id", "_kept", "_n_removed", "row", "key", "id", "kept", "packed", "label", "n_links", "class_id")
LONG = "word " * 60_000


def clashing(spark, rows):
    """Documents with columns that have the names of what stages compute."""
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{n}` string" for n in NAMES)
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), *NAMES) for i, t in rows], schema)


def test_stages_on_clashing_names_nulls_repeats_and_an_empty_table(spark, sf):
    passage = " ".join(f"p{i}" for i in range(70))
    rows = [(1, passage), (1, passage), (2, f"some words before it {passage} and some words behind it that make it differ enough from the first one, so that both stay, as one can see from this long tail of words"), (3, None), (None, "a text without an id"), (None, "a text without an id"), (4, ""), (5, LONG), (6, LONG)]
    docs = clashing(spark, rows)
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, sf)
        got = out.collect()
        assert out.columns == docs.columns and out.schema["n_words"] == docs.schema["n_words"], name
        assert all(tuple(r[n] for n in NAMES) == NAMES for r in got), name
        assert stage(spark, docs.limit(0), sf).count() == 0, name
        if name.startswith("n-gram"):
            assert sorted(((r["doc_id"] or 0, (r["text"] or "")[:6]) for r in got)) == [(0, "a text"), (1, "p0 p1 "), (2, "some w"), (3, ""), (4, ""), (5, "word w")]
        if name.startswith("substring"):
            texts = {r["doc_id"]: (r["text"], r["n_chars"]) for r in got}
            assert texts[1] == (passage, len(passage)) and "p0" not in texts[2][0] and texts[2][1] == len(texts[2][0])
            assert texts[3] == (None, 0) and texts[4] == ("", 0) and 6 not in texts and len(got) == len(rows) - 1
        if name.startswith("benchmark"):
            assert len(got) == len(rows)
    last = P.STAGES[-1][1](spark, docs, sf).collect()
    assert len(last) == len(rows) and {r["n_tokens"] for r in last if r["doc_id"] in (3, 4)} == {0}
    assert P.STAGES[-1][1](spark, docs.limit(0), sf).count() == 0
