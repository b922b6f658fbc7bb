"""Toxicity by a weighted finite-state pattern grammar.

A line becomes a string of symbols: a lexicon (a trie of stems, some given, others learnt from labelled rows as the shortest
prefixes that tell toxic texts) reads each word and writes insult, threat, target, negation, report or plain word, and
punctuation becomes the end of a sentence, a mark that speech runs over, or an opening or closing quotation. Three transducers
with explicit states and arcs rewrite that string:

* negation counts down the words that it reaches over and marks triggers among them; it ends with its clause;
* reported speech does the same with a longer reach, over commas, colons and quotation marks; a quotation that opens within the
  reach is reported as a whole, over ends of sentences too, and ends the state as it closes;
* the target transducer guesses at the start of a clause whether the clause names somebody and dies where the guess turns out
  wrong, so that triggers before the target are aimed too.

Their composition is computed once; its arcs that read a trigger write an event (insult or threat; aimed or loose; plain,
negated or reported) and carry that event's weight. A clause is scored by the path that survives to its end, and a text by
the logistic of the weights of its clauses' events, a thing said in n clauses counting log2(1 + n) times. Weights are fitted
by penalised likelihood around the grammar's own prior weights. Lines without a stem have no event, so only lines with a
hit of the stems' automaton are read symbol by symbol, which is exact.

Learnt stems are typed by the company they keep: a stem that mostly follows a word of intent within three words is a threat,
any other an insult. Given stems hold with and without accents on Latin letters, however composed; learnt stems keep the accents of the texts they
come from, which tell words apart. An elided French article or pronoun is a word of its own; apostrophes may be curly.

Defined results: null and empty texts emit no event and get the score of the intercept; texts are read whole; repeated rows
are scored alike; without labelled rows the prior weights and given stems hold; labels, lang, source and doc_id never enter a
score; other columns may have any name.
"""

from __future__ import annotations

import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from heapq import merge
from operator import itemgetter

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import boxed, sliced_texts, stored, table, unboxed
from .labelled import fit_logistic, held_out, logistic, training_rows

# The grammar's own words; stems have no accents, as they also meet folded words. A star at the end takes any ending.
INSULTS = "idiot* moron* loser* scum* trash pathetic worthless stupid* disgusting clown* dumb* fool* imbecile* cretin* bastard* asshole* bitch* vermin filth* creep* freak* jerk* garbage dimwit* halfwit* retard* subhuman* idiota* estupid* imbecil* basura inutil* cabron* pendej* dummkopf* arschloch* abschaum trottel* schwachkopf* versager* connard* salope* abruti* ordure* debile* cretine*".split()
THREATS = "kill* murder* hurt destroy* beat stab* shoot strangle* exterminat* matar* matare* umbringen toten zerstoren tuer* tuerai detruire".split()
TARGETS = frozenset("you your you're youre yours u ur yourself he she they them him her du dich dir dein deine ihr euch tu te ti usted ustedes vosotros vous toi votre vos tú".split())
NEGATIONS = frozenset("not no never isn't aren't wasn't don't doesn't didn't cannot can't won't without nicht kein keine nie nunca jamas sin ne pas jamais sans jamás".split())
REPORTS = frozenset("said says say wrote writes claimed claims quoted quote quotes called reported alleged told asked article sagte sagt schrieb dijo dice escribio dit ecrit escribió écrit".split())
INTENT = frozenset("will ll gonna going shall must should werde werden wirst voy vas vamos vais allons".split())
#: Words that negation and reported speech reach over.
REACH = {"negated": 3, "reported": 12}

EVENTS = tuple(f"{kind}/{aim}/{mood}" for kind in ("insult", "threat") for aim in ("aimed", "loose") for mood in ("plain", "negated", "reported"))
PLACE = {event: k for k, event in enumerate(EVENTS)}
#: Prior weights: what an event of each kind adds, then the intercept.
PRIOR = {"insult/aimed/plain": 5.0, "insult/loose/plain": 4.5, "threat/aimed/plain": 4.0, "threat/loose/plain": 0.5, "insult/aimed/negated": 0.5, "insult/loose/negated": 0.5, "threat/aimed/negated": 0.0, "threat/loose/negated": 0.0, "insult/aimed/reported": 0.8, "insult/loose/reported": 0.8, "threat/aimed/reported": 0.2, "threat/loose/reported": 0.0}
INTERCEPT = -3.0
STEM_LENGTHS = (4, 5, 6, 7)
#: Labelled rows that stems and weights are learnt from, at most.
TRAIN_ROWS = 20_000
#: A learnt stem is in so many toxic training texts and so many times as frequent there; the most frequent ones, at most so many.
STEM_SUPPORT, STEM_LIFT, STEM_LIMIT = 4, 25.0, 400
LINE_END = re.compile(r"[\n\r]")
QUOTES = re.compile(r"[\"“”„«»]")
#: Clause ends that reported speech runs over.
CARRIES = frozenset(',:"“”„«»')
WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")
#: A word, or a character that ends a clause.
TOKEN = re.compile(WORD.pattern + r"|[.,;:!?()\"“”„«»]")
MARKS = frozenset('.,;:!?()"“”„«»')
ELIDED = re.compile(r"(l|d|j|m|t|s|c|n|qu|jusqu|lorsqu|puisqu)'(?=[aeiouyhà-öø-ÿœ])")
#: Elided words that the grammar has in full.
IN_FULL = {"n": "ne", "t": "te"}
#: Small Latin letters with marks and the letter below; marks that no composed letter has.
PLAIN = {c: base[0] for c in map(chr, (*range(0xC0, 0x250), *range(0x1E00, 0x1F00))) if (base := unicodedata.normalize("NFD", c)) != c and "a" <= base[0] <= "z"}
ACCENTED, LOOSE_MARKS = re.compile(f"[{''.join(PLAIN)}]"), re.compile("(?<=[a-z])[\u0300-\u036f]+")


def lowered(text: str) -> str:
    """Small letters, composed, straight apostrophes."""
    low = text.lower()
    return low if low.isascii() else LOOSE_MARKS.sub("", unicodedata.normalize("NFC", low.replace("\u2019", "'")))


def folded(low: str) -> str:
    """A lowered text with Latin letters stripped of their marks, place by place."""
    return low if low.isascii() else ACCENTED.sub(lambda m: PLAIN[m[0]], low)


def words_in(text: str, start: int = 0, end: int | None = None) -> list[str]:
    """Words of a lowered text; what French elides before a vowel stands apart."""
    words = WORD.findall(text, start, len(text) if end is None else end)
    if "'" not in text:
        return words
    out = []
    for word in words:
        if cut := ELIDED.match(word):
            out += [IN_FULL.get(cut[1], cut[1]), word[cut.end() :]]
        else:
            out.append(word)
    return out

#: Given stems, which also match words that are spelled with accents.
GIVEN = {w.rstrip("*"): (kind, w.endswith("*")) for kind, words in (("threat", THREATS), ("insult", INSULTS)) for w in words}


def quotations(line: str) -> dict[int, int]:
    """Place of each opening quotation mark -> place of the mark that closes it; marks without a partner are left out."""
    found, opened = {}, None
    for mark in QUOTES.finditer(line):
        k = mark.start()
        loose, tight = not line[max(0, k - 1) : k].strip(), line[k + 1 : k + 2].isalnum()
        if opened is None or (loose and tight):
            # A mark behind a word or number that no word follows (5" of rain) opens nothing.
            opened = k if loose or tight or not line[k - 1].isalnum() else None
        else:
            found[opened], opened = k, None
    return found


TRIGGERS, WORDS = ("insult", "threat"), ("word", "target", "negation", "report")
BREAKS = ("stop", "carry", "open", "close", "end")


@dataclass
class Transducer:
    """arcs: state -> symbol read -> [(next state, symbol written)]; a path lives as long as there is an arc for it."""

    start: object
    arcs: dict[object, dict[str, list[tuple[object, str]]]]

    def run(self, symbols: list[str]) -> list[tuple[object, list[str]]]:
        """Every path over the symbols, as its last state and what it wrote."""
        paths = [(self.start, [])]
        for symbol in symbols:
            paths = [(after, [*out, written]) for state, out in paths for after, written in self.arcs[state].get(symbol, ())]
        return paths

    def then(self, other: Transducer) -> Transducer:
        """Composition: what this one writes the other reads; only pairs of states that can be reached are made."""
        start = (self.start, other.start)
        arcs, todo = {}, [start]
        while todo:
            pair = todo.pop()
            if pair in arcs:
                continue
            arcs[pair] = {symbol: [((x, y), out) for x, middle in ends for y, out in other.arcs[pair[1]].get(middle, ())] for symbol, ends in self.arcs[pair[0]].items()}
            todo += [after for ends in arcs[pair].values() for after, _ in ends]
        return Transducer(start, arcs)


def negation(reach: int = REACH["negated"]) -> Transducer:
    """States: words that negation still reaches over."""
    arcs = {}
    for k in range(reach + 1):
        after = max(0, k - 1)
        arcs[k] = {w: [(after, w)] for w in WORDS} | {b: [(0, b)] for b in BREAKS} | {t: [(after, f"{t} negated" if k else t)] for t in TRIGGERS}
        arcs[k]["negation"] = [(reach, "negation")]
    return Transducer(0, arcs)


def reporting(reach: int = REACH["reported"]) -> Transducer:
    """States: words that a report still reaches over, or being inside a reported quotation."""
    arcs = {}
    for k in [*range(reach + 1), "quoted"]:
        inside = k == "quoted"
        after = k if inside else max(0, k - 1)
        arcs[k] = {w: [(after, w)] for w in WORDS} | {f"{t} negated": [(after, f"{t} negated")] for t in TRIGGERS} | {t: [(after, f"{t} reported" if k else f"{t} plain")] for t in TRIGGERS}
        arcs[k] |= {"carry": [(k, "carry")], "stop": [(k if inside else 0, "stop")], "end": [(0, "end")], "open": [("quoted" if k else 0, "open")], "close": [(0 if inside else k, "close")]}
        if not inside:
            arcs[k]["report"] = [(reach, "report")]
    return Transducer(0, arcs)


def targeting() -> Transducer:
    """States: a clause that is to name somebody and hasn't yet, one that has, one that is to name nobody."""
    told = [f"{t} {mood}" for t in TRIGGERS for mood in ("plain", "negated", "reported")]
    event = lambda x, aim: "/".join((x.split()[0], aim, x.split()[1]))
    arcs: dict = {}
    for state in ("promised", "named", "nobody"):
        aim = "loose" if state == "nobody" else "aimed"
        arcs[state] = {w: [(state, "")] for w in WORDS} | {x: [(state, event(x, aim))] for x in told}
        # A clause ends and the next one begins with either guess; a promise that wasn't kept has no way on.
        arcs[state] |= {b: [] if state == "promised" else [("promised", "|"), ("nobody", "|")] for b in BREAKS}
    arcs["promised"]["target"] = arcs["named"]["target"] = [("named", "")]
    arcs["nobody"]["target"] = []
    # The first clause has both guesses too.
    arcs["begin"] = {symbol: [*arcs["promised"][symbol], *arcs["nobody"][symbol]] for symbol in arcs["nobody"]}
    return Transducer("begin", arcs)


@lru_cache(1)
def machine() -> Transducer:
    return negation().then(reporting()).then(targeting())


@dataclass
class Grammar:
    """stems: word or prefix -> (kind, takes any ending); weights in the order of EVENTS, the intercept last."""

    stems: dict[str, tuple[str, bool]] = field(default_factory=dict)
    weights: np.ndarray = field(default_factory=lambda: np.array([*(PRIOR[e] for e in EVENTS), INTERCEPT]))

    def __post_init__(self) -> None:
        if not self.stems:
            self.stems = dict(GIVEN)

    def automaton(self) -> ahocorasick.Automaton:
        trie = ahocorasick.Automaton()
        for stem in self.stems:
            trie.add_word(stem, stem)
        trie.make_automaton()
        return trie

    def kind_of(self, word: str) -> str | None:
        """What the trigger acceptors say of a word: the longest stem decides, of the word as spelled, then of its folded form."""
        for stems, form in ((self.stems, word), (GIVEN, folded(word))):
            for n in range(len(form), 2, -1):
                if (found := stems.get(form[:n])) and (n == len(form) or found[1]):
                    return found[0]
            if word.isascii():
                break
        return None

    def symbol(self, word: str) -> str:
        """The lexicon: what a word is to the transducers."""
        if kind := self.kind_of(word):
            return kind
        if word in NEGATIONS or word.endswith("n't"):
            return "negation"
        return "report" if word in REPORTS else "target" if word in TARGETS else "word"

    def symbols(self, line: str) -> list[str]:
        """A lowered line as the transducers read it."""
        pairs, out = quotations(line), []
        closing = set(pairs.values())
        for token in TOKEN.finditer(line):
            text, at = token[0], token.start()
            if text not in MARKS:
                out += [self.symbol(w) for w in words_in(text)]
            else:
                out.append("open" if at in pairs else "close" if at in closing else "carry" if text in CARRIES else "stop")
        out.append("end")
        return out

    def clauses(self, line: str) -> Iterator[set[str]]:
        """The events of each clause of a lowered line that has any, by the one path that lives to the clause's end."""
        arcs = machine().arcs
        live: dict[object, frozenset] = {machine().start: frozenset()}
        for symbol in self.symbols(line):
            following = {}
            for state, events in live.items():
                for after, written in arcs[state].get(symbol, ()):
                    following[after] = events | {written} if written and written != "|" else events
            live = following
            if symbol in BREAKS:
                events = next(iter(live.values()))
                if events:
                    yield set(events)
                    live = dict.fromkeys(live, frozenset())

    def events(self, text: str | None, trie: ahocorasick.Automaton) -> np.ndarray:
        """Clauses with each event, their number dampened so that long texts don't gain by length alone."""
        out = np.zeros(len(EVENTS))
        if not text:
            return out
        low, done = lowered(text), -1
        plain = folded(low)
        hits = trie.iter(low) if plain == low else merge(trie.iter(low), trie.iter(plain), key=itemgetter(0))
        for end, stem in hits:
            start = end - len(stem) + 1
            if start <= done or (start and low[start - 1].isalpha()):
                continue
            before = max(low.rfind("\n", 0, start), low.rfind("\r", 0, start)) + 1
            found = LINE_END.search(low, end)
            done = found.start() if found else len(low)
            for events in self.clauses(low[before:done]):
                out[[PLACE[e] for e in events]] += 1
        return np.log1p(out) / np.log(2)

    def score(self, text: str | None, trie: ahocorasick.Automaton) -> float:
        return float(logistic(self.events(text, trie) @ self.weights[:-1] + self.weights[-1]))


def any_stem(grammar: Grammar, text: str | None) -> bool:
    """The word list that the grammar is compared with: does any trigger occur?"""
    return any(grammar.kind_of(w) for w in words_in(lowered(text or "")))


def stem_counts(rows: DataFrame) -> DataFrame:
    """Texts of each label that hold each candidate stem, and toxic ones that have it after a word of intent: counted per
    partition first, then summed."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally: Counter = Counter()

        def out() -> pa.RecordBatch:
            items = list(tally.items())
            return pa.RecordBatch.from_arrays([pa.array([k[0] for k, _ in items], pa.string()), pa.array([k[1] for k, _ in items], pa.int32()), pa.array([n for _, n in items], pa.int64())], ["stem", "label", "n"])

        def stems_of(words: set[str]) -> set[str]:
            found = set()
            for word in words:
                found.update(word[:n] for n in STEM_LENGTHS if len(word) > n)
                if 3 <= len(word) <= 24:
                    found.add(word + "$")
            return found

        for batch in sliced_texts(batches, "text"):
            for text, label in zip(batch.column("text").to_pylist(), batch.column("label").to_pylist(), strict=True):
                words = words_in(lowered(text))
                tally.update((s, label) for s in stems_of(set(words)))
                if label == 1:
                    meant = {w for k, word in enumerate(words) if word in INTENT for w in words[k + 1 : k + 4]}
                    tally.update((s, 2) for s in stems_of(meant))
            if len(tally) > 300_000:
                yield out()
                tally.clear()
        yield out()

    of = lambda label: F.sum(F.when(F.col("label") == label, F.col("n")).otherwise(0))
    return rows.mapInArrow(count, "stem string, label int, n long").groupBy("stem").agg(of(1).alias("toxic"), of(0).alias("clean"), of(2).alias("meant"))


def learnt_stems(counts: DataFrame, toxic: int, clean: int, support: int = STEM_SUPPORT, lift: float = STEM_LIFT, limit: int = STEM_LIMIT) -> dict[str, tuple[str, bool]]:
    """Stems that are frequent in toxic texts and (nearly) absent from clean ones; of nested prefixes the shortest."""
    if not toxic or not clean:
        return {}
    ratio = (F.col("toxic") / toxic) / ((F.col("clean") + 0.5) / clean)
    found = counts.filter((F.col("toxic") >= max(support, toxic // 150)) & (ratio >= lift) & (F.col("clean") * 20 <= F.col("toxic"))).orderBy(F.desc("toxic"), "stem").limit(limit).collect()
    stems: dict[str, tuple[str, bool]] = {}
    for r in sorted(found, key=lambda r: (len(r["stem"]), r["stem"])):
        word = r["stem"].rstrip("$")
        if not any(word[:n] in stems and stems[word[:n]][1] for n in range(3, len(word) + 1)):
            stems[word] = ("threat" if 2 * r["meant"] > r["toxic"] else "insult", not r["stem"].endswith("$"))
    return stems


def fit_grammar(docs: DataFrame, labels: DataFrame, limit: int = TRAIN_ROWS) -> Grammar:
    """Learn stems and weights from at most `limit` labelled rows outside the held-out fold."""
    rows = stored(training_rows(docs, labels, "toxic", limit))
    sizes = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count("*").alias("n")).collect()}
    grammar = Grammar()
    learnt = learnt_stems(stem_counts(rows), sizes.get(1, 0), sizes.get(0, 0))
    grammar.stems = learnt | grammar.stems
    packed = rows.mapInArrow(lambda batches: _events(batches, grammar), "events binary, label int").collect()
    if packed:
        x = np.stack([np.frombuffer(r["events"], np.float64) for r in packed])
        y = np.array([r["label"] for r in packed], float)
        grammar.weights = fit_logistic(x, y, grammar.weights, 0.5)
    return grammar


def _events(batches: Iterator[pa.RecordBatch], grammar: Grammar) -> Iterator[pa.RecordBatch]:
    trie = grammar.automaton()
    for batch in sliced_texts(batches, "text"):
        events = [grammar.events(t, trie).tobytes() for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array(events, pa.binary()), batch.column("label")], ["events", "label"])


def score_toxicity(docs: DataFrame, grammar: Grammar, keep: list[str], text_col: str = "text", out: str = "score") -> DataFrame:
    """The kept columns and `out`: one scan, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = grammar.automaton()
        for batch in sliced_texts(batches, "text"):
            scores = pa.array([grammar.score(t, trie) for t in batch.column("text").to_pylist()], pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column("row"), scores], ["row", "score"])

    chosen = boxed(docs, keep, text_col)
    return unboxed(chosen.mapInArrow(run, chosen.select("row").schema.add("score", "double")), F.col("score").alias(out))


def op7_toxicity_grammar(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    grammar = fit_grammar(docs, table(spark, sf_dir, "labels"))
    scored = score_toxicity(docs, grammar, ["doc_id"])
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
