"""The other training-data operators against brute force, round trips and the edge cases that their docstrings define."""

import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from multiway.llm import bpe, chat, decontaminate, licences, quality, sharding, substring, topk, toxicity
from multiway.llm.queries import ORACLE, QUERIES

LONG = "word " * 40_000
EDGES = [(1, "plain words here, and more of them"), (2, ""), (3, None), (None, "no id"), (4, LONG), (5, "plain words here, and more of them"), (5, "plain words here, and more of them"), (6, "É日本 \x00 \t\r\n x")]
SCHEMA = "doc_id long, text string, slot int, score double, n_words long, label int"


@pytest.fixture(scope="module")
def edges(spark):
    return spark.createDataFrame([(i, t, 9, 9.0, 9, 9) for i, t in EDGES], SCHEMA)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


# Sharding


def test_shards_are_near_equal_and_gapless(spark, docs):
    rows = sharding.shard_records(docs, 8)[0].collect()
    size, places = Counter(), defaultdict(list)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in rows:
        raw = texts[r["doc_id"]].encode()
        assert r["size"] == len(raw) + 16 and r["text_crc32"] == zlib.crc32(raw)
        size[r["shard"]] += r["size"]
        places[r["shard"]].append(r["slot"])
    assert max(size.values()) < 1.05 * sum(size.values()) / 8
    assert all(sorted(p) == list(range(len(p))) for p in places.values())


def test_rebalancing_edits_the_map(spark, edges, nothing):
    weights = {s: 100 + s % 7 for s in range(4096)}
    m = sharding.SlotMap()
    m.plan(weights, 10)
    m.rebalance(weights, 11)
    before, after = m.versions
    moved = [s for s in range(4096) if before[s] != after[s]]
    assert all(after[s] == 10 for s in moved) and 0 < len(moved) < 4096 / 8
    assert sharding.SlotMap.from_frame(m.to_frame(spark)).versions == m.versions
    m.rebalance(weights, 5)
    assert set(m.current) == set(range(5))
    assert sharding.shard_records(edges, 3)[0].count() == len(EDGES)
    assert sharding.shard_records(nothing, 3)[0].count() == 0


def test_repeats_spread_over_slots_and_shards(spark):
    rows = [(7, "same text", 1)] * 2000 + [(None, "copy without id", 1)] * 500 + [(i, f"text {i}", 1) for i in range(2000)] + [(99_999, None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, slot int").repartition(5)
    placed = sharding.shard_records(docs, 8)[0].collect()
    size, places = Counter(), defaultdict(list)
    for r in placed:
        size[r["shard"]] += r["size"]
        places[r["shard"]].append(r["slot"])
    assert len(placed) == len(rows) and max(size.values()) < 1.05 * sum(size.values()) / 8
    assert all(sorted(p) == list(range(len(p))) for p in places.values())
    null = next(r for r in placed if r["doc_id"] == 99_999)
    assert (null["size"], null["text_crc32"]) == (16, 0)


def test_the_map_is_stored_by_version(spark, docs):
    from multiway.sources.storage import new_path

    path = new_path(spark, "map")
    _, one = sharding.shard_records(docs, 8, map_path=path)
    placed, two = sharding.shard_records(docs, 9, slot_map=sharding.SlotMap.load(spark, path), map_path=path)
    again = sharding.SlotMap.load(spark, path)
    assert again.versions == two.versions and again.versions[0] == one.versions[0] and len(again.versions) == 2
    assert {(r["virtual_slot"], r["shard"]) for r in placed.collect()} <= set(enumerate(again.current))
    assert {r["map_version"] for r in placed.collect()} == {1}


# Licences


def test_licence_families(spark, docs, edges, nothing):
    model = licences.fit_licences(docs)
    for line, family in (("Released under the MIT License.", "MIT"), ("Licensed under the Apache License, Version 2.0.", "Apache-2.0"), ("Licensed under CC BY-NC 4.0.", "CC-BY-NC"), ("This work is licensed under the GNU General Public License, version 3.", "GPL-3.0"), ("All rights reserved.", "Proprietary")):
        assert model.scan(f"Some text.\n{line}\nMore text.")[1][0][0] == family
    assert model.scan("The driver renewed a licence at the office.\nThe end.")[1] == []
    assert [r["n_paragraphs"] for r in licences.scan_licences(edges, model, edges.columns).collect()][1:3] == [0, 0]
    assert licences.scan_licences(nothing, licences.fit_licences(nothing), ["doc_id"]).count() == 0


def test_licences_against_plain_arithmetic(spark, sf, docs):
    """Every line of the whole table, scored by dictionary sums without the scan's shortcuts."""
    model = licences.fit_licences(docs)
    names = [*licences.FAMILIES, "unknown", None]

    def judged(line):
        words = licences.tokens(line)
        grams = {" ".join(words[i : i + n]) for n in (1, 2, 3) for i in range(len(words) - n + 1)}
        z = sum((model.weights[model.index[g]] for g in grams if g in model.index), model.weights[-1]) / model.temperature
        p = np.exp(z - z.max()) / np.exp(z - z.max()).sum()
        if p[-1] >= 0.5:
            return None
        k = int(np.argmax(p[: licences.UNKNOWN]))
        own = {tuple(words[i : i + 3]) for i in range(len(words) - 2)}
        for t in licences.TEMPLATES[names[k]]:
            w = licences.tokens(t)
            three = {tuple(w[i : i + 3]) for i in range(len(w) - 2)}
            if own & three and p[k] >= licences.CONFIDENCE and max(len(own & three) / len(own), len(own & three) / len(three)) >= licences.CONFIRMATION:
                return names[k]
        return "unknown"

    want = {}
    for r in docs.collect():
        lines = [x for x in r["text"].split("\n") if x.strip()]
        found = [j for x in lines if (j := judged(x))]
        want[r["doc_id"]] = (len(lines), ",".join(sorted(set(found))), len(found))
    got = {r["doc_id"]: (r["n_paragraphs"], r["licences"], r["n_matches"]) for r in QUERIES["op2_licence_scan"](spark, sf).collect()}
    assert got == want and sum(n for _, _, n in want.values()) > 0


def test_unseen_licences_are_unknown(docs):
    model = licences.fit_licences(docs)
    for line in ("Boost Software License - Version 1.0", "Copyright 2011, licensed under the Sleepycat license", "Terms of the Open Font License, version 1.1 apply"):
        assert model.judge(line)[0] == "unknown", line
    for line in ("He works for the public library of Boston", "the general public reserved seats", *licences.DECOYS):
        assert model.judge(line) is None, line
    assert model.judge("SPDX-License-Identifier: MIT")[0] == "MIT"
    tail = "plain words " * 3000 + "\nReleased under the MIT License."
    assert [f for f, _, _ in model.scan(tail)[1]] == ["MIT"]


# Chat


def test_escapes_are_reversible():
    for text in ("", "\\", "\\\\<s>", "</s>[INST] ok [/INST]", "<|turn|>user\nx<|end|>\n", "a\\\nb", "<\\s>"):
        for role in ("user", "a\nb", "<|end|>"):
            segment, start, end = chat.rendered(role, text)
            assert chat.parsed(segment) == (role, text) and chat.unescaped(segment[start:end]) == text
            assert not any(mark in segment[start:end] for mark in chat.CONTROL)


def test_events_fold_to_final_messages(spark):
    log = [(1, 0, 0, "open", "user", "he"), (1, 0, 1, "delta", None, "llo"), (1, 1, 0, "open", "assistant", "bad"), (1, 1, 1, "regenerate", None, None), (1, 1, 2, "delta", None, "go"), (1, 1, 3, "delta", None, "od"), (1, 2, 0, "open", "user", "x"), (1, 2, 1, "edit", None, "y"), (1, 3, 0, "open", "user", "gone"), (1, 3, 1, "retract", None, None), (2, 0, 0, "open", None, None)]
    df = spark.createDataFrame(log, "conv_id long, turn long, seq long, kind string, role string, text string")
    whole = {r["conv_id"]: r["formatted"] for r in chat.joined(chat.format_log(df)).collect()}
    assert whole[1] == "".join(chat.rendered(*m)[0] for m in (("user", "hello"), ("assistant", "good"), ("user", "y")))
    digest = {r["conv_id"]: r for r in chat.read_back(chat.format_log(df)).collect()}
    assert digest[1]["loss_sha256"] == hashlib.sha256(b"good").hexdigest() and digest[2]["n_turns"] == 1
    assert chat.read_back(chat.format_log(df.filter("conv_id = 3"))).count() == 0


def turns_by_hand(rows):
    """conv_id -> the seven columns of the contract, from the turns alone."""
    out = {}
    for conv in {r[0] for r in rows}:
        own = sorted(((turn is not None, turn or 0, role or "", text or "") for c, turn, role, text, *_ in rows if c == conv))
        loss = "".join(t for _, _, role, t in own if role == "assistant")
        whole = "".join(chat.rendered(role, t)[0] for _, _, role, t in own)
        out[conv] = (len(own), hashlib.sha256("".join(f"{role}\n{t}\n" for _, _, role, t in own).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(whole))
    return out


def test_turns_become_deltas_edits_and_regenerations(spark):
    rows = [(1, 0, "user", "a\\b", 5, "x"), (1, 1, "assistant", "é日本" * 30_000, 5, "x"), (1, 1, "assistant", "twice", 5, "x"), (1, 1, "assistant", "twice", 5, "x"), (1, None, None, None, 5, "x"), (2, 0, "assistant", "", 5, "x"), (2, 1, "assistant", None, 5, "x"), (3, 0, "user", "<s>[INST]<|end|>", 5, "x"), (None, 0, "assistant", "no id", 5, "x")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, seq int, kind string")
    log = chat.events_of_turns(turns)
    assert {r["kind"] for r in log.select("kind").distinct().collect()} == {"open", "delta", "regenerate", "edit"}
    got = {r["conv_id"]: (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"], r["formatted_chars"]) for r in chat.read_back(chat.format_log(log)).collect()}
    assert got == turns_by_hand(rows)


# Top-k


def test_top_k_is_exact(spark):
    random = np.random.default_rng(0)
    vectors = [(i, (random.standard_normal(6) + 4 * (i % 3)).tolist()) for i in range(300)]
    vectors += [(300 + i, vectors[0][1]) for i in range(60)] + [(400, None), (401, [float("nan")] * 6), (402, [1.0, None]), (403, [float("inf")]), (None, [1.0] * 6), (7, vectors[7][1]), (7, vectors[8][1])] + [(50, vectors[50][1])] * 9
    df = spark.createDataFrame([(i, v, 1, 1) for i, v in vectors], "vec_id long, embedding array<double>, vec int, cell int")
    got = defaultdict(list)
    from pyspark.sql import functions as F

    for r in topk.voronoi_top_k(topk.quantised(df), F.col("vec_id") % 50 == 0, 5, pivots=8, query_rows=3, data_rows=64).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    x = [(i, np.floor(np.array(v, float) * 256).astype(int)) for i, v in vectors if v is not None and i is not None and None not in v and np.isfinite(v).all()]
    for q in {i for i, _ in x if i % 50 == 0}:
        pairs = [(i, int(v @ w)) for j, w in x if j == q for i, v in x if i != q]
        assert got[q] == sorted(pairs, key=lambda t: (-t[1], t[0]))[:5]
    assert topk.voronoi_top_k(topk.quantised(df.filter("vec_id < 0")), F.lit(True)).count() == 0
    assert topk.voronoi_top_k(topk.quantised(df.filter("vec_id < 3")), F.lit(True)).count() == 6
    assert topk.voronoi_top_k(topk.quantised(df.filter("vec_id = 50")), F.lit(True)).count() == 0
    big = topk.products(np.array([[2**40, 1]]), np.array([[2**20, 3]]))
    assert big[0, 0] == 2**60 + 3


# Classifiers


@pytest.mark.parametrize(("fit", "score", "label", "least"), [(quality.fit_quality, quality.score_quality, "quality", 0.95), (toxicity.fit_grammar, toxicity.score_toxicity, "toxic", 0.9)])
def test_held_out_accuracy(spark, edges, nothing, fit, score, label, least):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = fit(docs, labels)
    rows = [r for r in score(docs, model, ["doc_id"]).join(labels, "doc_id").collect() if zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1]
    at = 0.5 if label == "quality" else 0.7
    assert np.mean([(r["score"] >= at) == r[label] for r in rows]) >= least
    got = score(edges, model, ["doc_id"], out="mine").collect()
    assert len(got) == len(EDGES) and all(0 <= r["mine"] <= 1 for r in got)
    assert score(nothing, fit(nothing, labels), ["doc_id"]).count() == 0


@pytest.mark.parametrize("text", ["a b a b a b", "One two  one, TWO!! 77%%\n|x| é", "x", " ", "the cat the cat sat on the mat on the mat"])
def test_quality_ngrams_by_hand(text):
    from multiway.llm.common import WordHashes

    raw, want, base = text.encode(), set(), int(quality.STARTS[-1])
    kinds = [int(quality.KINDS[b]) for b in raw]
    kinds = [k for i, k in enumerate(kinds) if i < 2 or not (k == kinds[i - 1] == kinds[i - 2])]
    words = raw.lower().split()
    repeat = [2 if i and words[i - 1] == w else 1 if w in words[max(0, i - quality.REPEATS) : i] else 0 for i, w in enumerate(words)]
    for seq, size, first in ((kinds, quality.ALPHABET, 0), (repeat, 3, quality.ORDER)):
        for n in range(1, quality.ORDER + 1):
            for i in range(len(seq) - n + 1):
                code = 0
                for c in seq[i : i + n]:
                    code = code * size + c
                want.add(int(quality.STARTS[first + n - 1]) + code)
    got = set(quality.active(text, WordHashes()).tolist())
    assert {c for c in got if c < base} == want
    assert len({c for c in got if c >= base}) == len(set(words)) + len(set(zip(words, words[1:], strict=False)))


def test_the_fit_does_not_depend_on_the_order_of_rows(spark):
    d = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    one, two = (quality.fit_quality(x, y) for x, y in ((docs, labels), (docs.repartition(7), labels.repartition(3))))
    assert (one.weights == two.weights).all() and one.offset == two.offset


def test_grammar_weighs_clauses():
    grammar = toxicity.Grammar()
    trie = grammar.automaton()
    s = lambda text: grammar.score(text, trie)
    assert s("you are an idiot") > 0.7 > s("you are not an idiot")
    assert s("he said you are an idiot") < 0.7 and s("clean text") < 0.1 and s(None) == s("")


def paths_by_hand(symbols):
    """Events of each clause from all paths through the three transducers, one after the other, nothing composed."""
    found = [out for _, first in toxicity.negation().run(symbols) for _, second in toxicity.reporting().run(first) for _, out in toxicity.targeting().run(second)]
    clauses = {tuple(tuple(sorted({e for e in part.split() if e})) for part in " ".join(out).split("|")[:-1]) for out in found}
    assert len(clauses) == 1  # the guesses of a clause that its end bears out are one path
    return [set(c) for c in clauses.pop() if c]


def test_composition_equals_all_paths():
    random = np.random.default_rng(4)
    symbols = ["word", "word", "target", "negation", "report", "insult", "threat", "carry", "stop", "open", "close"]
    grammar = toxicity.Grammar()
    for _ in range(400):
        line = [*random.choice(symbols, random.integers(0, 12)).tolist(), "end"]
        grammar.symbols = lambda _, line=line: line
        assert list(grammar.clauses("")) == paths_by_hand(line), line
    machine = toxicity.machine()
    assert {state[0][0] for state in machine.arcs} == {0, 1, 2, 3} and {state[0][1] for state in machine.arcs} >= {0, 12, "quoted"}


#: Sentences that hold a stem each; whether they are toxic lies in the clause.
CONTRAST = [("you are an idiot", 1), ("idiot, that is what you are", 1), ("what a worthless clown", 1), ("we will kill you", 1), ("I am going to murder him", 1), ("du bist ein Dummkopf", 1), ("eres un cabrón", 1), ("tu es un abruti", 1), ("they are all scum", 1), ("shut up, you pathetic loser", 1)] + [(t, 0) for t in ("you are not an idiot", "he said you are an idiot", 'she wrote: "you are a moron"', "kill the process and restart it", "the frost will destroy the harvest", "a drum beat and a second drum beat", "it wasn't stupid", "the article called him a clown", "tu n'es pas idiot", "er schrieb, du bist ein Versager", "the acid can hurt", "nobody said that you are worthless")]


def test_clauses_tell_more_than_stems(spark):
    d = "/root/testdata/sf0.01"
    fitted = toxicity.fit_grammar(spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"))
    for grammar in (toxicity.Grammar(), fitted):
        trie = grammar.automaton()
        right = sum((grammar.score(t, trie) >= 0.7) == y for t, y in CONTRAST)
        listed = sum(toxicity.any_stem(grammar, t) == y for t, y in CONTRAST)
        print("right of", len(CONTRAST), "grammar", right, "any stem", listed)
        assert right >= 20 and listed == sum(y for _, y in CONTRAST) == 10


def test_learnt_stems_are_typed(spark):
    texts = [(f"we will zorble you {i}", 1) for i in range(6)] + [(f"you are a grombat {i}", 1) for i in range(6)] + [(f"plain words {i}", 0) for i in range(40)]
    rows = spark.createDataFrame(texts, "text string, label int")
    stems = toxicity.learnt_stems(toxicity.stem_counts(rows), 12, 40, lift=2.0)
    kinds = {w: k for w, (k, _) in stems.items()}
    assert {k for w, k in kinds.items() if w.startswith("zorb")} == {"threat"} and {k for w, k in kinds.items() if w.startswith("grom")} == {"insult"}


def test_training_rows_are_one_an_id(spark):
    from multiway.llm.labelled import training_rows

    docs = spark.createDataFrame([(i % 40, f"t{i:03}", 1) for i in range(200)], "doc_id long, text string, label int")
    labels = spark.createDataFrame([(i % 40, i % 2, 0) for i in range(80)] + [(None, 1, 0), (3, 7, 0)], "doc_id long, quality int, toxic int")
    rows = training_rows(docs, labels, "quality", 10).collect()
    assert len(rows) == 10 == len({r["doc_id"] for r in rows})
    assert all(r["text"] == f"t{r['doc_id']:03}" and zlib.crc32(str(r["doc_id"]).encode()) % 3 != 1 for r in rows)


@pytest.mark.parametrize("text", ["eres un estúpido", "quel imbécile", "eres un cabrón", "tu es débile", "eres un inútil", "c'est l'abruti du village", "un tas d'ordure", "tu es l’idiot", "QUEL IMBÉCILE", "quel imbe\u0301cile"])
def test_accented_and_elided_insults(text):
    grammar = toxicity.Grammar()
    trie = grammar.automaton()
    assert grammar.events(text, trie).sum() == 1 and grammar.score(text, trie) > 0.7


def test_accented_threats_and_context_words():
    grammar = toxicity.Grammar()
    trie = grammar.automaton()
    found = lambda text: [toxicity.EVENTS[i] for i in np.flatnonzero(grammar.events(text, trie))]
    assert found("wir werden dich töten") == found("wir werden dich zerstören") == ["threat/aimed/plain"]
    assert found("il a écrit que c'est un abruti") == found("escribió que es un cabrón") == ["insult/loose/reported"]
    assert found("il n'est abruti") == found("it isn’t stupid") == found("jamás un idiota") == ["insult/loose/negated"]
    assert toxicity.folded(toxicity.lowered("Ça й が 한")) == "ca й が 한" and toxicity.words_in("don't d'accord l'x") == ["don't", "d", "accord", "l'x"]
    learnt = toxicity.Grammar({"réeux": ("insult", True), "reeuy": ("insult", True)} | toxicity.GIVEN)
    assert [learnt.kind_of(w) for w in ("réeuxai", "reeuxai", "reeuyai", "réeuyai", "imbéciles")] == ["insult", None, "insult", None, "insult"]


def test_reported_speech_runs_over_punctuation():
    grammar = toxicity.Grammar()
    trie = grammar.automaton()
    moods = lambda text: [toxicity.EVENTS[i].split("/")[2] for i in np.flatnonzero(grammar.events(text, trie))]
    quoted = "one two three four five six seven eight nine ten eleven twelve thirteen."
    for text in ('he said, "you are an idiot"', "she wrote: you are an idiot", "she wrote: “you are an idiot”", "il a dit : « quel idiot »", f'he said: "{quoted} You are an idiot!"', 'He said 5" of rain, you are an idiot', 'He asked "why" and "how", then said "you idiot"'):
        assert moods(text) == ["reported"] and grammar.score(text, trie) < 0.7, text
    for text in ('he said "hello", you are an idiot', "he said hello. You are an idiot", "he said hello\nyou are an idiot", f"he said, {quoted[:-1]} you idiot", '"hello", you idiot', f'he said: "{quoted[:-1]} you are an idiot'):
        assert moods(text) == ["plain"] and grammar.score(text, trie) > 0.7, text
    assert moods("not today, you idiot") == ["plain"] and moods("he said, you are not an idiot") == ["negated"]


# Tokens


def test_tokens_match_the_library(spark, edges, nothing):
    tiktoken = pytest.importorskip("tiktoken")
    import public_tokenizers as P

    ranks = bpe.read_ranks(bpe.default_ranks_path())
    want = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    ours = bpe.Encoder(ranks, P.PATTERN)
    random = np.random.default_rng(0)
    texts = ["a" * 500, " " * 90 + "x", "\n\n \t", "é" * 99, "it's we'll", "<|endoftext|>", *("".join(chr(c) for c in random.choice([32, 97, 98, 233, 10, 46, 0x65E5, 0x1F600], 200)) for _ in range(30))]
    for t in texts:
        assert ours.encode(t) == want.encode_ordinary(t) and ours.decode(ours.encode(t)) == t.encode()
    rows = bpe.encoded(edges, ["doc_id"], ids=True)
    back = bpe.decoded(rows, ["doc_id"]).collect()
    assert sorted((r["text"] for r in back)) == sorted((t or "" for _, t in EDGES))
    assert bpe.encoded(nothing, ["doc_id"]).count() == 0


def test_token_digests_of_the_whole_table(spark, sf, docs):
    tiktoken = pytest.importorskip("tiktoken")
    import public_tokenizers as P

    want = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(bpe.default_ranks_path()), special_tokens={})
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    rows = QUERIES["op8_byte_bpe"](spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        ids = want.encode_ordinary(texts[r["doc_id"]])
        assert (r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest())


# Decontamination


def brute_hits(text, items, width=10):
    words = decontaminate.words_of(text)
    hit, found = set(), set()
    for item, t in items:
        w = decontaminate.words_of(t)
        n = min(width, len(w))
        windows = {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()
        for i in range(len(words) - n + 1):
            if n and tuple(words[i : i + n]) in windows:
                hit |= set(range(i, i + n))
                found.add(str(item))
    return len(words), len(hit), sorted(found)


@pytest.mark.parametrize("limit", [1 << 20, 400])
def test_decontamination(spark, docs, sf, limit):
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()] + [(90, "short item"), (91, ""), (92, None), (93, "Short ITEM!")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    extra = spark.createDataFrame([(-1, "A short, item here"), (-2, None), (-3, " ".join(items[0][1].split()[1:14]))], "doc_id long, text string")
    all_docs = docs.select("doc_id", "text").unionByName(extra)
    texts = {r["doc_id"]: r["text"] for r in all_docs.collect()}
    got = {r["row"]["doc_id"]: (r["n_words"], r["n_hit"], sorted(r["hit_items"])) for r in decontaminate.decontaminate(all_docs, bench, ["doc_id"], broadcast_bytes=limit).collect()}
    assert got == {i: brute_hits(t, items) for i, t in texts.items()}
    if limit > 1000:
        clean = decontaminate.without_spans(all_docs, bench)
        assert decontaminate.without_contaminated(all_docs, bench).count() == sum(not g[1] for g in got.values())
        assert "short" not in {r["doc_id"]: r["text"] for r in clean.collect()}[-1]
        assert decontaminate.decontaminate(all_docs, bench.limit(0), ["doc_id"]).filter("n_hit > 0").count() == 0


def test_windows_are_small_at_ten_times_a_slice(spark):
    random = np.random.default_rng(2)
    vocabulary = [f"w{i}" for i in range(3000)]
    texts = [" ".join(random.choice(vocabulary, 200)) for _ in range(400)]
    size = sum(map(len, texts))
    whole = decontaminate.Windows(list(enumerate(texts)))
    assert whole.nbytes < 6 * size
    bench = spark.createDataFrame(list(enumerate(texts)) + [(None, texts[0]), (None, "a short one")], "item_id long, text string")
    docs = spark.createDataFrame([(i, "x " + " ".join(t.split()[20:40]) + " y", 1, 2, 3) for i, t in enumerate(texts)] + [(900, None, 1, 2, 3), (901, "a short one", 1, 2, 3), (902, "", 1, 2, 3)], "doc_id long, text string, n_words int, key int, row int")
    slices = decontaminate._item_slices(bench, size // 10)
    assert len(slices) >= 10 and max(sum(len(r["text"]) for r in s.collect()) for s in slices) < size // 4
    rows = {r["row"]["doc_id"]: r for r in decontaminate.decontaminate(docs, bench, docs.columns, broadcast_bytes=size // 10).collect()}
    for i in range(400):
        assert rows[i]["n_hit"] == 20 and str(i) in rows[i]["hit_items"] and rows[i]["hit_ranges"] == [1, 21]
    assert (rows[901]["n_hit"], rows[901]["hit_items"]) == (3, []) and rows[900]["n_words"] == 0 and rows[902]["n_hit"] == 0
    assert decontaminate.without_contaminated(docs, bench).columns == docs.columns
    cut = {r["doc_id"]: r["text"] for r in decontaminate.without_spans(docs, bench).collect()}
    assert cut[5].split() == ["x", "y"] and cut[900] is None


# Substrings


def brute_kept(rows, width=13):
    first = {}
    for d, t in rows:
        w = (t or "").encode().split()
        for i in range(len(w) - width + 1):
            if d is not None:
                first[tuple(w[i : i + width])] = min(d, first.get(tuple(w[i : i + width]), d))
    out = []
    for d, t in rows:
        w = (t or "").encode().split()
        gone = set()
        for i in range(len(w) - width + 1):
            if d is not None and first[tuple(w[i : i + width])] < d:
                gone |= set(range(i, i + width))
        out.append((d if d is not None else -9, len(w), len(gone), b" ".join(x for i, x in enumerate(w) if i not in gone).decode()))
    return sorted(out)


def substring_rows(df):
    return sorted((r["row"]["doc_id"] if r["row"]["doc_id"] is not None else -9, r["n_words"], r["n_removed"], r["kept"] or "") for r in df.collect())


def test_substrings_in_one_batch_and_in_many(spark, docs, nothing):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    passage = " ".join(f"p{i}" for i in range(60))
    rows += [(5000, passage), (5001, f"a {passage} b"), (5002, None), (None, passage), (5003, ""), (5001, passage), (-5, " ".join(passage.split()[:13]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert substring_rows(substring.dedup_batch(df, ["doc_id"])) == brute_kept(rows)
    from multiway.sources.storage import new_path

    index = substring.SubstringIndex(spark, new_path(spark, "index"), 4, fanout=1)
    got = []
    for part in (df.filter("doc_id < 60"), df.filter("doc_id >= 60 AND doc_id < 150"), df.filter("doc_id >= 150 OR doc_id IS NULL")):
        got += substring_rows(index.dedup(part, ["doc_id"]))
        index = substring.SubstringIndex.open(spark, index.path)
    assert sorted(got) == brute_kept(rows) and len(index.runs) <= 2 and max(t for t, _ in index.runs) == 1
    # A batch that was lost before its manifest leaves the index as it was, and can be fed again.
    before = list(index.runs)
    lost = substring.SubstringIndex.open(spark, index.path)
    lost._write(substring.runs_of(df.filter("doc_id < 9"), 4).filter("bucket >= 0"))
    lost.spark.createDataFrame([(0, "half", 4, 13, 1)], "tier int, run string, n_buckets int, width int, fanout int").write.option("mapreduce.fileoutputcommitter.marksuccessfuljobs", "false").parquet(f"{index.path}/manifest-99")
    assert substring.SubstringIndex.open(spark, index.path).runs == before
    assert substring.dedup_batch(nothing, ["doc_id"]).count() == 0


def test_buckets_follow_the_text(spark):
    df = spark.createDataFrame([(1, "x" * 1000)], "doc_id long, text string")
    assert substring.buckets_for(df) == 8
    old, substring.BUCKET_BYTES = substring.BUCKET_BYTES, 20
    try:
        assert substring.buckets_for(df) == 50
    finally:
        substring.BUCKET_BYTES = old


def test_packing_keeps_values():
    random = np.random.default_rng(0)
    for values in (np.empty(0, np.uint64), np.array([0], np.uint64), np.sort(random.integers(0, 1 << 63, 5000).astype(np.uint64)), np.array([0, 1, 2**64 - 1], np.uint64)):
        assert (substring.unpack_sorted(substring.pack_sorted(values)) == values).all()
    ids = np.array([-(2**62), -1, 0, 5, 2**62])
    assert (substring.unpack_ids(substring.pack_ids(ids)) == ids).all()


def test_all_queries_are_registered():
    numbers = {int(n[2:].split("_")[0]) for n in QUERIES}
    assert numbers == set(range(1, 11)) and set(ORACLE) <= set(QUERIES)
