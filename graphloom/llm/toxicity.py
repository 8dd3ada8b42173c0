"""Toxicity by a weighted finite-state pattern grammar.

Two transducers are composed. The first maps a word to a symbol (insult, threat, target, negation,
report, or nothing); its lexicon is a set of words and stems, a small built-in one and one learnt from
labelled documents. The second reads the symbols of one clause and emits an event at each insult or
threat, named by the clause's context: negated or not, reported or not, aimed at a target or not. A
clause scores the weights of its events, so a word counts by the clause it stands in. A document's
events are weighed by a logistic model fitted on the same bounded sample.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.llm.common import arrow_rows, by_bytes, lean, slices, texts
from graphloom.llm.quality import SCORED, in_fold, judge

INSULT, THREAT, TARGET, NEGATION, REPORT, END = 1, 2, 3, 4, 5, 6
#: Small public word lists. Fixed values.
WORDS = {
    INSULT: "idiot moron scum loser pathetic worthless trash disgusting stupid clown dumb imbecile cretin bastard pig vermin filth garbage coward creep jerk fool ugly freak",
    THREAT: "kill murder hurt destroy strangle stab shoot beat burn hang lynch slaughter",
    TARGET: "you your yours he she they them his her their people tu toi vous votre ton ta du dich ihr euch sie dein dir usted ustedes vosotros ellos",
    NEGATION: "not never no isn't aren't wasn't don't doesn't ne pas jamais nicht kein keine nie nunca jamás",
    REPORT: "said says called wrote quoted claims reported dit écrit sagte schrieb dijo escribió",
}
POSITIVE_ROWS, NEGATIVE_ROWS = 1500, 12_000
_STEMS = (4, 5, 6, 7, 8)
_STRIP = ".,;:!?\"'()[]{}<>*#$%&-_|«»¿¡"
_BREAKS = ".,;:!?"
EVENTS = 16  # (insult, threat) x negated x reported x aimed


@dataclass
class Lexicon:
    """The word transducer: whole words and stems, each with its symbol."""

    words: dict[str, int] = field(default_factory=dict)
    stems: dict[str, int] = field(default_factory=dict)

    def symbol(self, word: str) -> int:
        found = self.words.get(word, 0)
        if not found and self.stems:
            for n in _STEMS:
                if len(word) < n:
                    break
                if found := self.stems.get(word[:n], 0):
                    break
        return found


def built_in() -> Lexicon:
    return Lexicon({w: symbol for symbol, line in WORDS.items() for w in line.split()})


class WordSymbols(dict):
    """Symbols of a chunk of text: its word's symbol, and whether a clause ends with it; a bounded memory."""

    def __init__(self, lexicon: Lexicon, most: int = 150_000):
        super().__init__()
        self.lexicon, self.most = lexicon, most

    def __missing__(self, chunk: str) -> bytes:
        symbol = self.lexicon.symbol(chunk.strip(_STRIP).lower())
        value = (bytes([symbol]) if symbol else b"") + (bytes([END]) if chunk[-1] in _BREAKS else b"")
        if len(self) >= self.most:
            self.clear()
        if len(chunk) <= 40:
            self[chunk] = value
        return value


def _clause_table() -> tuple[list[list[int]], list[list[int]]]:
    """The clause transducer: next state and event (or -1) by state and symbol. A state is three bits: negated, reported, aimed."""
    after = [[0] * 7 for _ in range(8)]
    event = [[-1] * 7 for _ in range(8)]
    for state in range(8):
        for symbol in range(7):
            after[state][symbol] = {END: 0, NEGATION: state | 1, REPORT: state | 2, TARGET: state | 4}.get(symbol, state)
            if symbol in (INSULT, THREAT):
                event[state][symbol] = (symbol - 1) * 8 + state
                after[state][symbol] = state & ~1  # a negation spends itself on the next match
    return after, event


AFTER, EVENT = _clause_table()
_MATCHING = bytes([INSULT, THREAT])
_SILENT = bytes(x for x in range(256) if x not in _MATCHING)


def clause_events(text: str, symbols: WordSymbols) -> tuple[list[int], int]:
    """How often each event is emitted in a text, and how many of its clauses match. Lines end clauses too."""
    counts = [0] * EVENTS
    clauses = 0
    for line in text.split("\n"):
        tape = b"".join([symbols[c] for c in line.split()])
        if not tape.translate(None, _SILENT):
            continue
        state, hit = 0, False
        for s in tape:
            if (e := EVENT[state][s]) >= 0:
                counts[e] += 1
                hit = True
            state = AFTER[state][s]
            if s == END:
                clauses += hit
                hit = False
        clauses += hit
    return counts, clauses


def _features(counts: list[list[int]], clauses: list[int]) -> np.ndarray:
    """Log counts of the events, of matching clauses, and a constant."""
    x = np.log1p(np.array(counts, float).reshape(-1, EVENTS))
    return np.c_[x, np.log1p(np.array(clauses, float)), np.array(clauses) > 0, np.ones(len(x))]


def _prior() -> np.ndarray:
    """Weights before any label: an aimed match weighs more, a negated or reported one less."""
    w = [0.9 + 0.6 * bool(e & 4) - 0.6 * bool(e & 1) - 0.6 * bool(e & 2) for e in range(EVENTS)]
    return np.array([*w, 0.5, 1.0, -2.0])


def fit_weights(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 30) -> np.ndarray:
    """Logistic weights near the prior, by Newton steps."""
    prior = _prior()
    w = prior.copy()
    for _ in range(steps if len(y) else 0):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + ridge * (w - prior)
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= np.clip(step, -1, 1)
        if np.abs(step).max() < 1e-6:
            break
    return w


@dataclass
class ToxicityModel:
    lexicon: Lexicon
    weights: np.ndarray

    def scorer(self):
        """A function from a column of texts to scores, with a word memory of its own."""
        symbols = WordSymbols(self.lexicon)

        def score(column: pa.Array) -> np.ndarray:
            got = [clause_events(t, symbols) for t in texts(column)]
            x = _features([c for c, _ in got], [k for _, k in got])
            return 1 / (1 + np.exp(-np.clip(x @ self.weights, -30, 30)))

        return score


def _terms(chunk: str) -> list[str]:
    word = chunk.strip(_STRIP).lower()
    return [f"={word}", *(word[:n] for n in _STEMS if len(word) >= n)] if len(word) >= 3 else []


TERM = "term string, toxic int, context bigint, n bigint"


def _count_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each term and label of the sample: documents that hold it and up to 32 contexts (the words before), of a partition."""
    n: Counter = Counter()
    contexts: dict[tuple[str, int], set[int]] = {}
    known: dict[str, list[str]] = {}
    for b in (part for batch in batches for part in slices(batch, 1)):
        for label, text in zip(b.column(0).to_pylist(), texts(b.column(1)), strict=True):
            held: set[str] = set()
            before = ""
            for chunk in text.split():
                terms = known.get(chunk)
                if terms is None:
                    terms = known[chunk] = _terms(chunk)
                    if len(known) > 50_000:
                        known.clear()
                held.update(terms)
                if label:
                    seen = zlib.crc32(before.encode())
                    for t in terms:
                        own = contexts.setdefault((t, 1), set())
                        if len(own) < 32:
                            own.add(seen)
                before = chunk
            for t in held:
                n[t, label] += 1
    rows: dict[str, list] = {"term": [], "toxic": [], "context": [], "n": []}
    for (t, label), count in n.items():
        for i, c in enumerate(contexts.get((t, label), {0})):
            for k, v in zip(rows, (t, label, c, count if i == 0 else 0), strict=True):
                rows[k].append(v)
    yield arrow_rows(TERM, rows)


def learn_lexicon(sample: DataFrame, positives: int, negatives: int) -> Lexicon:
    """Words and stems that mark toxic documents of the sample, beyond what chance would give the best of all terms.

    Support counts different contexts, not documents, so that the words of one much-copied document don't pass.
    """
    out = built_in()
    if not positives or not negatives:
        return out
    share = positives / (positives + negatives)
    least = math.ceil(math.log(1e7) / math.log(1 / share))
    grouped = (
        sample.mapInArrow(lean(_count_terms), TERM)
        .groupBy("term")
        .agg(F.sum(F.when(F.col("toxic") == 1, F.col("n"))).alias("p"), F.coalesce(F.sum(F.when(F.col("toxic") == 0, F.col("n"))), F.lit(0)).alias("q"), F.count_distinct(F.when(F.col("toxic") == 1, F.col("context"))).alias("contexts"))
        .where((F.col("contexts") >= min(least, 24)) & (F.col("p") >= min(least, 24)) & (F.col("q") <= 0.02 * F.col("p")))
        .orderBy(F.desc("p"), "term")
        .limit(20_000)
    )
    found = {r.term: r.p for r in grouped.collect()}
    heads: dict[str, int] = {}  # of each stem, the support of its strongest single word
    for t, p in found.items():
        if t.startswith("="):
            out.words.setdefault(t[1:], INSULT)
            for n in _STEMS:
                heads[t[1 : n + 1]] = max(heads.get(t[1 : n + 1], 0), p)
    for t in sorted((t for t in found if not t.startswith("=")), key=len):
        # a stem stands for several words; one that a single word explains stays that word
        if heads.get(t, 0) < 0.6 * found[t] and not any(t[:n] in out.stems for n in _STEMS if n < len(t)):
            out.stems[t] = INSULT
    return out


def fit_toxicity(docs: DataFrame, labels: DataFrame, positive_rows: int = POSITIVE_ROWS, negative_rows: int = NEGATIVE_ROWS) -> ToxicityModel:
    """Learn lexicon and weights on a bounded sample of labelled rows outside the held-out fold."""
    usable = labels.where(labels["toxic"].isNotNull() & labels["doc_id"].isNotNull() & ~in_fold(labels["doc_id"]))
    ids = usable.select(labels["doc_id"].cast("bigint").alias("doc_id"), labels["toxic"].cast("int").alias("toxic"))
    order = [F.xxhash64("doc_id"), "doc_id"]
    chosen = F.broadcast(ids.where("toxic = 1").orderBy(*order).limit(positive_rows).union(ids.where("toxic = 0").orderBy(*order).limit(negative_rows)))
    sample = by_bytes(docs).select(docs["doc_id"].cast("bigint").alias("doc_id"), docs["text"]).join(chosen, "doc_id").select("toxic", "text")
    sizes = {r.toxic: r["n"] for r in sample.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    lexicon = learn_lexicon(sample, sizes.get(1, 0), sizes.get(0, 0))
    schema = "toxic int, " + ", ".join(f"e{i} int" for i in range(EVENTS)) + ", clauses int"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        symbols = WordSymbols(lexicon)
        for b in (part for batch in batches for part in slices(batch, 1)):
            got = [clause_events(t, symbols) for t in texts(b.column(1))]
            yield arrow_rows(schema, {"toxic": b.column(0), **{f"e{i}": [c[i] for c, _ in got] for i in range(EVENTS)}, "clauses": [k for _, k in got]})

    rows = sorted(tuple(r) for r in sample.mapInArrow(lean(run), schema).collect())
    x = _features([r[1:-1] for r in rows], [r[-1] for r in rows])
    y = np.array([r[0] for r in rows], float)
    return ToxicityModel(lexicon, fit_weights(x, y))


def score_toxicity(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """(doc_id, score) of each row of docs. A document without a matching clause has the constant's score; so have null and empty texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = model.scorer()
        for b in (part for batch in batches for part in slices(batch, 1)):
            yield arrow_rows(SCORED, {"doc_id": b.column(0), "score": score(b.column(1))})

    return by_bytes(docs).select(docs["doc_id"].cast("bigint"), docs["text"]).mapInArrow(lean(run), SCORED)


def classify_toxicity(docs: DataFrame, labels: DataFrame, least: float = 0.5) -> DataFrame:
    """One row a document: higher scores are likelier toxic 1. Repeated rows repeat; extra columns are not read."""
    return judge(score_toxicity(docs, fit_toxicity(docs, labels)), least)
