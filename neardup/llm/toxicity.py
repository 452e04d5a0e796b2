"""Operator 4: toxicity by a weighted lexicon, matched by Aho-Corasick on folded text.

Folding: lower case, zero-width characters dropped, homoglyphs and digit substitutions turned into
the Latin letters they stand for. A term counts where it begins a word. Terms are the word
beginnings that tell the labels apart on the training rows; their weights are log odds. Exceptions are pairs of
neighbouring words around a term that only harmless training rows have, and phrases that the caller gives; hits inside
one don't count. The weight found, alone and divided by the length of the text, goes through a
logistic function that is fitted on the same rows.

Cases: null or empty text scores as a text without a hit; repeated rows score alike; rows of labels
without a document, with a null label or more than one label for a document are all used as they are;
without training rows of both labels the lexicon is empty and every score is the base rate; very long texts are
matched whole; of equal terms one counts; further columns of documents and labels, whatever their names, are not read.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.session import ship_package

#: At most so many labelled rows are learned from, drawn by hash of their id.
TRAIN_ROWS = 20_000
TERMS = 2_000
SHORTEST, LONGEST = 4, 10
LEAST_DOCS = 4
LEAST_PRECISION = 0.9
#: Lookalike letters of other scripts and digits or signs that stand for letters.
HOMOGLYPHS = {"а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "і": "i", "ј": "j", "ѕ": "s", "ԁ": "d", "һ": "h", "к": "k", "м": "m", "т": "t", "в": "b", "н": "h", "α": "a", "ε": "e", "ο": "o", "ρ": "p", "ν": "v", "τ": "t", "ι": "i", "κ": "k", "υ": "u", "ı": "i", "ɑ": "a", "ɡ": "g"}
DIGITS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i"}
ZERO_WIDTH = "​‌‍⁠﻿­"
#: A pair of words is an exception if so many harmless training rows have it and no toxic one.
EXCEPTION_ROWS = 3
EXCEPTIONS = 2_000


def _table() -> dict[int, str | None]:
    table: dict[int, str | None] = {ord(k): v for k, v in {**HOMOGLYPHS, **DIGITS}.items()}
    table |= {0xFF41 + i: chr(97 + i) for i in range(26)} | {0xFF10 + i: DIGITS.get(str(i), str(i)) for i in range(10)}
    return table | {ord(c): None for c in ZERO_WIDTH}


FOLD = _table()


def fold(text: str) -> str:
    return text.lower().translate(FOLD)


def _starts(text: str) -> set[str]:
    """Beginnings of the folded words of a text, of all lengths that terms can have."""
    words = {w.strip(".,;:()[]\"'?#*%&|<>-") for w in fold(text).split()}
    return {w[:n] for w in words for n in range(SHORTEST, min(LONGEST, len(w)) + 1)}


def training_rows(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS) -> DataFrame:
    """Distinct (text, toxic) of at most so many rows whose id isn't held out."""
    known = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where(F.col("toxic").isin(0, 1) & (F.crc32(F.col("doc_id").cast("string")) % 5 != 0))
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(most)
    return docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select("text", "toxic").dropDuplicates()


def learn_terms(rows: DataFrame, terms: int = TERMS) -> dict[str, float]:
    """Word beginnings with their log odds, the shortest that is as telling as its continuations."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = (Counter(), Counter())
            for t, y in zip(b.column(0), b.column(1), strict=True):
                found[y.as_py()].update(_starts(t.as_py() or ""))
            # A beginning that only harmless rows of the batch have still lowers its odds elsewhere.
            keys = list(found[0].keys() | found[1].keys())
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([found[1][k] for k in keys], pa.int64()), pa.array([found[0][k] for k in keys], pa.int64())], ["term", "bad", "good"])

    counts = rows.mapInArrow(count, "term string, bad bigint, good bigint").groupBy("term").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    telling = counts.where((F.col("bad") >= LEAST_DOCS) & (F.col("bad") >= LEAST_PRECISION * (F.col("bad") + F.col("good"))))
    found = {r.term: (r.bad, r.good) for r in telling.orderBy(F.desc("bad"), F.length("term"), "term").limit(20 * terms).collect()}
    chosen: dict[str, float] = {}
    for term, (bad, good) in sorted(found.items(), key=lambda x: (len(x[0]), x[0])):
        if len(chosen) < terms and not any(term[:n] in chosen for n in range(SHORTEST, len(term))):
            chosen[term] = math.log((bad + 0.5) / (good + 0.5))
    return chosen


def _pairs_around(folded: str, start: int, end: int) -> Iterator[str]:
    """The word that holds a hit together with the one before it, and with the one behind it."""
    stop = end
    while stop < len(folded) and folded[stop].isalnum():
        stop += 1
    word = folded[start:stop]
    before, behind = folded[:start].rsplit(None, 1)[-1:], folded[stop:].split(None, 1)[:1]
    if before and folded[start - 1] == " " and before[0].isalnum():
        yield f"{before[0]} {word}"
    if behind and folded[stop] == " " and behind[0].isalnum():
        yield f"{word} {behind[0]}"


def learn_exceptions(rows: DataFrame, terms: dict[str, float], most: int = EXCEPTIONS) -> tuple[str, ...]:
    """Pairs of neighbouring words around a term that harmless training rows have, EXCEPTION_ROWS or more, and no toxic one."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon(terms)
        for b in batches:
            found = (Counter(), Counter())
            for t, y in zip(b.column(0), b.column(1), strict=True):
                folded = fold(t.as_py() or "")
                found[y.as_py()].update({p for s, e, _ in lexicon.hits_in(folded) for p in _pairs_around(folded, s, e)})
            keys = list(found[0].keys() | found[1].keys())
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([found[1][k] for k in keys], pa.int64()), pa.array([found[0][k] for k in keys], pa.int64())], ["pair", "bad", "good"])

    if not terms:
        return ()
    counts = rows.mapInArrow(count, "pair string, bad bigint, good bigint").groupBy("pair").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    harmless = counts.where((F.col("bad") == 0) & (F.col("good") >= EXCEPTION_ROWS)).orderBy(F.desc("good"), "pair").limit(most)
    return tuple(r.pair for r in harmless.collect())


class Lexicon:
    """Finds terms at word beginnings, outside exception phrases."""

    def __init__(self, terms: dict[str, float], exceptions: tuple[str, ...] = ()):
        import ahocorasick

        self.machine = ahocorasick.Automaton()
        for t, w in terms.items():
            self.machine.add_word(t, (len(t), w))
        for e in exceptions:
            e = fold(e)
            self.machine.add_word(e, (len(e), None))
        if len(self.machine):
            self.machine.make_automaton()

    def hits(self, text: str) -> list[tuple[int, int, float]]:
        return self.hits_in(fold(text))

    def hits_in(self, folded: str) -> list[tuple[int, int, float]]:
        """(start, end, weight) in a folded text."""
        if not len(self.machine):
            return []
        found = [(end - n + 1, end + 1, w) for end, (n, w) in self.machine.iter(folded) if end < n or not folded[end - n].isalnum()]
        spans = [(s, e) for s, e, w in found if w is None]
        return [x for x in found if x[2] is not None and not any(s <= x[0] and x[1] <= e for s, e in spans)]

    def features(self, text: str | None) -> tuple[float, float]:
        """Weight found, and weight for each 100 characters, both damped."""
        if not text:
            return 0.0, 0.0
        total = sum(w for *_, w in self.hits(text))
        return math.log1p(max(0.0, total)), math.log1p(max(0.0, 100 * total / (len(text) + 100)))


def fit_logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1e-2, steps: int = 50) -> np.ndarray:
    """Weights of a logistic function with an intercept, by Newton's method."""
    x = np.column_stack((np.ones(len(x)), x))
    w = np.zeros(x.shape[1])
    ridge = penalty * np.eye(x.shape[1])
    ridge[0, 0] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + ridge, x.T @ (p - y) + ridge @ w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def train(docs: DataFrame, labels: DataFrame, exceptions: tuple[str, ...] = ()) -> tuple[dict[str, float], tuple[str, ...], list[float]]:
    """Terms with weights, exceptions, and the weights of the logistic function."""
    ship_package(docs.sparkSession)
    rows = training_rows(docs, labels)
    terms = learn_terms(rows)
    exceptions = tuple(dict.fromkeys((*exceptions, *learn_exceptions(rows, terms))))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon(terms, exceptions)
        for b in batches:
            made = [lexicon.features(t.as_py()) for t in b.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array([m[0] for m in made], pa.float64()), pa.array([m[1] for m in made], pa.float64()), b.column(1)], ["a", "b", "toxic"])

    seen = rows.mapInArrow(measure, "a double, b double, toxic int").toArrow()  # at most TRAIN_ROWS rows of three numbers
    if seen.num_rows == 0:
        return terms, exceptions, [math.log(0.01 / 0.99), 0.0, 0.0]
    order = np.lexsort((seen["toxic"].to_numpy(), seen["b"].to_numpy(), seen["a"].to_numpy()))
    x = np.column_stack((seen["a"].to_numpy(), seen["b"].to_numpy()))[order]
    return terms, exceptions, fit_logistic(x, seen["toxic"].to_numpy()[order]).tolist()


def score_documents(docs: DataFrame, labels: DataFrame, exceptions: tuple[str, ...] = ()) -> DataFrame:
    """One row (doc_id, held_out, score, predicted) for each document."""
    terms, exceptions, weights = train(docs, labels, exceptions)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon(terms, exceptions)
        for b in batches:
            made = [lexicon.features(t.as_py()) for t in b.column(1)]
            scores = [1 / (1 + math.exp(-max(-30.0, min(30.0, weights[0] + weights[1] * p + weights[2] * q)))) for p, q in made]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(scores, pa.float64()), pa.array([int(s >= 0.5) for s in scores], pa.int32())], ["doc_id", "score", "predicted"])

    scored = docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, score double, predicted int")
    return scored.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 5 == 0).alias("held_out"), "score", "predicted")


def held_out_report(scored: DataFrame, labels: DataFrame) -> DataFrame:
    """One row (n, n_toxic, accuracy, precision, recall) over the held-out rows of scored that have a label."""
    known = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where(F.col("toxic").isin(0, 1))
    both = scored.where("held_out").join(known, "doc_id")
    share = lambda of, among: F.try_divide(F.sum((of & among).cast("int")), F.sum(among.cast("int")))
    toxic, said = F.col("toxic") == 1, F.col("predicted") == 1
    return both.agg(F.count("*").alias("n"), F.sum("toxic").alias("n_toxic"), F.avg((toxic == said).cast("double")).alias("accuracy"), share(toxic, said).alias("precision"), share(said, toxic).alias("recall"))
