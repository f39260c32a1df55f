"""A weighted finite-state pattern grammar for toxic clauses.

Small transducers read a text's symbols one after the other, each rewriting what the one before it
wrote, and are composed into one table:

* the *lexicon* turns words into symbols: insults and violent verbs with a weight, intents ("will"),
  targets, negations, reports of speech, and ends of clauses;
* *negation* marks insults and violence that follow a negation by at most ``SCOPE`` words;
* *report* marks those that follow a report of speech in its clause;
* *threat* writes a threat where intent, violence and target meet in a clause: violence without
  both is a weak event;
* *target* marks the end of a clause that names a target, which makes its insults aimed ones.

What is scored are clauses: the weights of a clause's events by class (plain, aimed, negated or
reported insult; threat, damped threat, bare violence). A logistic curve over the sums of classes,
the heaviest clause and the share of hits gives the score. Fitting learns a weight for each class,
drawn towards the grammar's own ones, and completes the lexicon: a word, or a beginning of words,
that is significantly bound to the label becomes an insult with its log odds as weight.

Null and empty texts score like any text without a hit; texts are scored one by one, so repeated
rows get equal scores. Null labels do not count; several labels of a document count each, and of
several texts of one doc_id the first in order is learned from. Without labelled texts of both
kinds the general grammar is used. An empty table gives no row. Columns not asked for are not read;
a column of the input named ``score`` cannot be kept beside the score.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strel.llm.encode import blocks, each, tidy
from strel.runtime import materialize, ship

#: Labelled texts the lexicon and the curve are fitted on, at most (those of smallest hash).
FIT_ROWS = 20_000
#: Entries of a learned lexicon, at most (those of most evidence).
LEXICON = 4_000
#: Words that a negation reaches.
SCOPE = 3
#: Chunks whose symbols a task remembers before it starts afresh.
CACHE_CHUNKS = 100_000

# General words of the grammar.
INSULTS = "idiot idiots moron morons stupid loser losers scum trash pathetic worthless disgusting clown imbecile dumbass bastard asshole bitch fool dummkopf arschloch abschaum connard imbécile salaud crétin idiota estúpido imbécil basura".split()
VIOLENCE = "kill murder hurt destroy beat strangle töten umbringen sterben tuer mourir matar morir".split()
INTENTS = "will i'll we'll they'll gonna going want must should werde werden will vais allons veux voy vamos quiero".split()
TARGETS = "you your yours u ur they them their he him she her du dich dein ihr euch sie tu toi ton ta vous ils elle tú te usted ustedes ellos".split()
NEGATIONS = "not no never isn't aren't wasn't don't won't nobody kein keine nicht nie pas jamais aucun non ni nunca ningún".split()
REPORTS = "said says wrote quoted called claims claimed sagte schrieb behauptet dit écrit dijo escribió dicen".split()

_STRIP = " \t\r\n.,;:!?\"'()[]{}<>«»„“”‚‘’…*#$%&|_~`^=+/\\-"
_STOPS = (b".", b"!", b"?", b";", b":")
_BEGINNINGS = (4, 5, 6)
_MARKS = ("", "-", "~", "-~")
#: What transducers read and write: words, marked insults, violence and threats (- negated, ~ reported), ends of clauses.
SYMBOLS = ["other", "intent", "target", "negation", "report", "stop", "aimed stop", *(k + m for k in ("insult", "violence", "threat") for m in _MARKS)]
_CODE = {name: k for k, name in enumerate(SYMBOLS)}
#: Classes of events, and the grammar's own weights of them.
CLASSES = {"insult": 1.2, "aimed insult": 2.2, "negated insult": 0.2, "reported insult": 0.5, "threat": 4.5, "damped threat": 0.8, "violence": 0.2}
_OWN = (-2.5, *CLASSES.values(), 0.5, 0.0)


class Transducer:
    """A letter-to-letter transducer: ``step`` and ``write`` by state and symbol; state 0 begins."""

    def __init__(self, step: np.ndarray, write: np.ndarray):
        self.step, self.write = step, write

    @classmethod
    def of(cls, states: int, rule) -> Transducer:
        """From a rule (state, symbol) -> (state, symbol) over names of symbols."""
        step, write = np.zeros((states, len(SYMBOLS)), int), np.zeros((states, len(SYMBOLS)), int)
        for s in range(states):
            for a, name in enumerate(SYMBOLS):
                to, out = rule(s, name)
                step[s, a], write[s, a] = to, _CODE[out]
        return cls(step, write)

    def then(self, other: Transducer) -> Transducer:
        """The composition: ``other`` reads what this one writes. Only reachable states are kept."""
        states, todo = {(0, 0): 0}, [(0, 0)]
        step, write = [], []
        for s, o in todo:
            seen = self.write[s]
            write.append(other.write[o, seen])
            row = []
            for pair in zip(self.step[s].tolist(), other.step[o, seen].tolist(), strict=True):
                if pair not in states:
                    states[pair] = len(states)
                    todo.append(pair)
                row.append(states[pair])
            step.append(row)
        return Transducer(np.array(step), np.array(write))

    def run(self, symbols: list[int]) -> list[int]:
        state, out, step, write = 0, [], self.step.tolist(), self.write.tolist()
        for a in symbols:
            out.append(write[state][a])
            state = step[state][a]
        return out


def negation() -> Transducer:
    """States: words that a negation still reaches."""

    def rule(left: int, a: str) -> tuple[int, str]:
        if a == "negation":
            return SCOPE, a
        if a == "stop":
            return 0, a
        return max(0, left - 1), a + "-" if left and a in ("insult", "violence") else a

    return Transducer.of(SCOPE + 1, rule)


def report() -> Transducer:
    """State 1: behind a report of speech."""

    def rule(said: int, a: str) -> tuple[int, str]:
        if a in ("report", "stop"):
            return int(a == "report"), a
        return said, a + "~" if said and a in ("insult", "insult-", "violence", "violence-") else a

    return Transducer.of(2, rule)


def threat() -> Transducer:
    """States: 0-3 whether target (1) and intent (2) have been named, 4-7 violence meant, no target yet."""

    def rule(s: int, a: str) -> tuple[int, str]:
        if a == "stop":
            return 0, a
        if a.startswith("violence"):
            mark = a.removeprefix("violence")
            if s == 3:
                return s, "threat" + mark
            return (4 + _MARKS.index(mark), "other") if s == 2 else (s, a)
        if s >= 4:
            return (3, "threat" + _MARKS[s - 4]) if a == "target" else (s, a)
        return s | (a == "target") | 2 * (a == "intent"), a

    return Transducer.of(8, rule)


def target() -> Transducer:
    """State 1: the clause has named a target."""
    return Transducer.of(2, lambda s, a: (0, "aimed stop" if s else "stop") if a == "stop" else (s | (a == "target") | a.startswith("threat"), a))


@cache
def machine() -> tuple[list[list[int]], list[list[int]]]:
    """Steps and writings of the composed transducers."""
    t = negation().then(report()).then(threat()).then(target())
    return t.step.tolist(), t.write.tolist()


def _class_of(event: int, aimed: bool) -> int:
    """The place among ``CLASSES`` of an event in a clause."""
    names = list(CLASSES)
    kind = SYMBOLS[event]
    if kind.startswith("insult"):
        return names.index("negated insult" if "-" in kind else "reported insult" if "~" in kind else "aimed insult" if aimed else "insult")
    if kind.startswith("threat"):
        return names.index("threat" if kind == "threat" else "damped threat")
    return names.index("violence")


_EVENTS = {(e, aimed): _class_of(e, aimed) for e in range(_CODE["insult"], len(SYMBOLS)) for aimed in (False, True)}
_OTHER, _STOP, _AIMED = _CODE["other"], _CODE["stop"], _CODE["aimed stop"]
_VERBS = {w: 1.0 for w in VIOLENCE}
_KINDS = {w: _CODE[k] for k, ws in (("target", TARGETS), ("intent", INTENTS), ("negation", NEGATIONS), ("report", REPORTS)) for w in ws}


@dataclass
class Grammar:
    """A lexicon with weights, and the curve that turns weights of classes into a score."""

    words: dict[str, float] = field(default_factory=dict)
    beginnings: dict[str, float] = field(default_factory=dict)
    curve: tuple[float, ...] = _OWN

    def weight(self, word: str) -> float:
        w = self.words.get(word, 0.0)
        for n in _BEGINNINGS:
            if len(word) >= n:
                w = max(w, self.beginnings.get(word[:n], 0.0))
        return w

    def symbol(self, chunk: bytes) -> tuple[int, float, bool]:
        """The lexicon transducer: a white-space separated chunk to symbol, weight, and whether a clause ends."""
        word = chunk.decode("utf-8", "replace").strip(_STRIP).lower()
        stop = chunk.endswith(_STOPS)
        if word in _VERBS:
            return _CODE["violence"], max(_VERBS[word], self.words.get(word, 0.0)), stop
        w = self.weight(word) if word else 0.0
        return (_CODE["insult"], w, stop) if w else (_KINDS.get(word, _OTHER), 0.0, stop)

    def clauses(self, symbols: list[tuple[int, float, bool]]) -> Iterator[list[float]]:
        """Weights by class of every clause that holds an event."""
        step, write = machine()
        state, events, pending = 0, [], 1.0
        for a, w, stop in [*symbols, (_OTHER, 0.0, True)]:
            e = write[state][a]
            state = step[state][a]
            if w:
                pending = w
            if e > _AIMED:
                events.append((e, w or pending))  # a threat weighs as its verb
            if stop:
                aimed = write[state][_STOP] == _AIMED
                state = step[state][_STOP]
                if events:
                    found = [0.0] * len(CLASSES)
                    for e, w in events:
                        found[_EVENTS[e, aimed]] += w
                    yield found
                    events = []

    def features(self, symbols: list[tuple[int, float, bool]]) -> list[float]:
        found = list(self.clauses(symbols))
        hits = sum(1 for x in symbols if x[1])
        if not found:
            return [0.0] * (len(CLASSES) + 2)
        heaviest = max(sum(w * m for w, m in zip(c, CLASSES.values(), strict=True)) for c in found)
        return [*(math.log1p(sum(c)) for c in zip(*found, strict=True)), math.log1p(heaviest), math.log1p(100.0 * hits / len(symbols))]

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.curve[0] + x @ np.asarray(self.curve[1:])
        return 1.0 / (1.0 + np.exp(-np.clip(z, -30, 30)))


def general() -> Grammar:
    return Grammar({w: 3.0 for w in INSULTS}, {})


class _Reader:
    """Features of texts; symbols of chunks are remembered, as chunks recur."""

    def __init__(self, grammar: Grammar, limit: int = CACHE_CHUNKS):
        self.g, self.limit, self.known, self.hits = grammar, limit, {}, set()

    def features(self, texts: list[bytes]) -> np.ndarray:
        out = np.zeros((len(texts), len(CLASSES) + 2))
        for k, t in enumerate(texts):
            chunks = t.split()
            if len(self.known) > self.limit:
                self.known.clear()
                self.hits.clear()
            kinds = set(chunks)
            for c in kinds.difference(self.known):
                self.known[c] = self.g.symbol(c)
                if self.known[c][1]:
                    self.hits.add(c)
            if not self.hits.isdisjoint(kinds):
                out[k] = self.g.features([self.known[c] for c in chunks])
        return out


def _entries(text: str) -> set[str]:
    """What a text may teach: its words (``=word``) and the beginnings of its words (``^begin``)."""
    words = {w for c in text.split() if (w := c.strip(_STRIP).lower())}
    return {"=" + w for w in words} | {"^" + w[:n] for w in words for n in _BEGINNINGS if len(w) >= n}


def _count(batches: Iterator) -> Iterator:
    seen = (Counter(), Counter())
    for b in batches:
        for t, y in zip(each(b.column("text")), each(b.column("y")), strict=True):
            seen[y].update(_entries(t or ""))
    keys = list(seen[0] | seen[1])
    for at in range(0, len(keys), 50_000):
        part = keys[at : at + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array(part), pa.array([seen[1][k] for k in part], pa.int64()), pa.array([seen[0][k] for k in part], pa.int64())], ["entry", "pos", "neg"])


def _fit_curve(x: np.ndarray, y: np.ndarray, ridge: float = 0.1) -> tuple[float, ...]:
    """Logistic regression drawn towards the grammar's own weights, by Newton steps that are cut
    until the loss falls."""
    a = np.column_stack([np.ones(len(x)), x])
    own = np.array(_OWN)
    pull = np.full(a.shape[1], ridge)
    pull[0] = 1e-3

    def loss(w: np.ndarray) -> float:
        z = a @ w
        return float(np.logaddexp(0, z).sum() - y @ z + 0.5 * pull @ (w - own) ** 2)

    w, now = own.copy(), loss(own)
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        h = (a * (p * (1 - p))[:, None]).T @ a + np.diag(pull)
        step, cut = np.linalg.solve(h, a.T @ (y - p) - pull * (w - own)), 1.0
        while cut > 1e-6 and loss(w + cut * step) > now:
            cut /= 2
        if cut <= 1e-6 or now - loss(w + cut * step) < 1e-9:
            break
        w = w + cut * step
        now = loss(w)
    return tuple(float(v) for v in w)


def fit(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS) -> Grammar:
    """A grammar from labelled texts: ``labels`` has doc_id and toxic; at most ``rows`` are used."""
    ship(docs.sparkSession)
    some = labels.where("toxic IN (0, 1) AND doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("y"))
    some = some.orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(rows).groupBy("doc_id").agg(F.collect_list("y").alias("ys"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(some), "doc_id")
    texts = texts.groupBy("doc_id", "ys").agg(F.min("text").alias("text"))
    texts = materialize(texts.select("text", F.explode("ys").alias("y")), "labelled")
    counts = texts.mapInArrow(_count, "entry string, pos long, neg long").groupBy("entry").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    n1, n0 = (int(v or 0) for v in texts.agg(F.sum("y"), F.sum(1 - F.col("y"))).first())
    grammar = general()
    if not n1 or not n0:
        return grammar
    surprise = math.log((n1 + n0) / n1)
    bound = counts.where(F.col("pos") >= 3).where(F.col("neg") <= 0.1 * F.col("pos"))
    bound = bound.where(F.col("pos") * surprise >= 10.0).orderBy(F.col("pos").desc(), "entry").limit(2 * LEXICON)
    found = {r["entry"]: (r["pos"], r["neg"]) for r in bound.collect()}
    odds = {e: math.log((p + 0.5) / (n1 + 1)) - math.log((n + 0.5) / (n0 + 1)) for e, (p, n) in found.items()}
    for e in sorted(found, key=lambda e: (len(e), e)):
        if e[0] == "^" and not any(e[1 : 1 + n] in grammar.beginnings for n in _BEGINNINGS if n < len(e) - 1):
            grammar.beginnings[e[1:]] = max(0.5, odds[e])
    for e in found:
        if e[0] == "=" and not any(e[1 : 1 + n] in grammar.beginnings for n in _BEGINNINGS):
            grammar.words[e[1:]] = max(0.5, odds[e])
    got = texts.select("y", _features(grammar)(F.col("text")).alias("x")).collect()  # at most ``rows``
    grammar.curve = _fit_curve(np.array([r["x"] for r in got], dtype=float), np.array([r["y"] for r in got], dtype=float))
    return grammar


def _features(grammar: Grammar):
    @F.arrow_udf("array<double>")
    def features(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        reader = _Reader(grammar)
        for b in batches:
            yield pa.array([x for _, ts in blocks(range(len(b)), each(b)) for x in reader.features(ts).tolist()], pa.list_(pa.float64()))

    return features


def _scores(grammar: Grammar):
    @F.arrow_udf("double")
    def scores(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        reader = _Reader(grammar)
        for b in batches:
            yield pa.array([x for _, ts in blocks(range(len(b)), each(b)) for x in grammar.score(reader.features(ts)).tolist()], pa.float64())
        del reader
        tidy()

    return scores


def score(docs: DataFrame, grammar: Grammar, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """``keep`` columns of ``docs`` and the score, from 0 to 1, of every whole text.

    Only the text goes to Python and only the score comes back; other columns stay in the JVM.
    """
    ship(docs.sparkSession)
    return docs.select(*keep, _scores(grammar)(F.col(text_col).cast("string")).alias("score"))
