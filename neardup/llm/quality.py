"""Operator 8: quality rules as a short-circuit cascade.

Each rule reads one group of features. On a sample the cascade measures what a rule costs and how
many documents it rejects, then runs the rules by rejection per cost, each on what the ones before
it left. The order never changes which documents stay, only what is computed on the way.

Words are runs of characters other than space and 0x09-0x0D. Cases: null or empty text has zero
in every feature and is rejected as too short; repeated rows and null ids map one to one; a table
without rows keeps the order of RULES; very long texts form a slice of their own.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.common import IS_SPACE, GOLDEN, gram_hash, mix, prefix_hash, range_hash, slices, texts_of, tidy, word_bounds
from neardup.session import ship_package

SAMPLE = 400
WINDOW = 5
SYMBOLS = b"#*$%&|<>"
IS_SYMBOL = np.zeros(256, bool)
IS_SYMBOL[list(SYMBOLS)] = True


@dataclass(frozen=True)
class Rule:
    """Rejects where 100 * left > limit * right (or < for below), by integer features."""

    name: str
    group: str
    left: str
    limit: int
    right: str | None = None
    below: bool = False

    def rejects(self, f: dict[str, np.ndarray]) -> np.ndarray:
        left = f[self.left] * (100 if self.right else 1)
        limit = self.limit * f[self.right] if self.right else self.limit
        return left < limit if self.below else left > limit


#: The two first rules are the base; the others are the cascade's own verdict.
BASE_RULES = (
    Rule("too_short", "words", "n_words", 10, below=True),
    Rule("repeats", "repeats", "n_repeat_words", 20, "n_words"),
)
RULES = (
    *BASE_RULES,
    Rule("short_words", "words", "word_chars", 200, "n_words", below=True),
    Rule("long_words", "words", "word_chars", 2000, "n_words"),
    Rule("symbols", "symbols", "n_symbols", 40, "n_words"),
    Rule("copied_lines", "lines", "n_dup_lines", 50, "n_lines"),
)


class Features:
    """Features of the texts of a slice, each group made when it is first asked for."""

    def __init__(self, buf: np.ndarray, offs: np.ndarray):
        self.buf, self.offs, self.n = buf, offs, len(offs) - 1
        self._made: dict[str, dict[str, np.ndarray]] = {}
        self._base: dict[str, tuple] = {}

    def group(self, name: str) -> dict[str, np.ndarray]:
        if name not in self._made:
            self._made[name] = getattr(self, f"_{name}")()
        return self._made[name]

    def _bounds(self):
        if "bounds" not in self._base:
            self._base["bounds"] = word_bounds(self.buf, self.offs)
        return self._base["bounds"]

    def _sums(self):
        if "sums" not in self._base:
            self._base["sums"] = prefix_hash(self.buf)
        return self._base["sums"]

    def _by_row(self, flags: np.ndarray) -> np.ndarray:
        total = np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))
        return total[self.offs[1:]] - total[self.offs[:-1]]

    def _words(self) -> dict[str, np.ndarray]:
        _, _, rows = self._bounds()
        return {"n_words": np.bincount(rows, minlength=self.n), "word_chars": self._by_row(~IS_SPACE[self.buf] & ((self.buf & 0xC0) != 0x80))}

    def _symbols(self) -> dict[str, np.ndarray]:
        return {"n_symbols": self._by_row(IS_SYMBOL[self.buf])} | self.group("words")

    def _lines(self) -> dict[str, np.ndarray]:
        feeds = np.flatnonzero(self.buf == 10)
        starts = np.concatenate((self.offs[:-1], feeds + 1))
        order = np.argsort(starts, kind="stable")
        rows = np.concatenate((np.arange(self.n), np.searchsorted(self.offs, feeds, side="right") - 1))[order]
        starts = starts[order]
        ends = np.empty_like(starts)
        ends[:-1] = np.where(rows[1:] == rows[:-1], starts[1:] - 1, self.offs[rows[:-1] + 1])
        if len(ends):
            ends[-1] = self.offs[rows[-1] + 1]
        inside = np.concatenate(([0], np.cumsum(~IS_SPACE[self.buf])))
        real = inside[ends] > inside[starts]
        starts, ends, rows = starts[real], ends[real], rows[real]
        keys = mix(range_hash(self._sums(), starts, ends) + rows.astype(np.uint64) * GOLDEN)
        _, first = np.unique(keys, return_index=True)
        n_lines = np.bincount(rows, minlength=self.n)
        return {"n_lines": n_lines, "n_dup_lines": n_lines - np.bincount(rows[first], minlength=self.n)}

    def _repeats(self) -> dict[str, np.ndarray]:
        starts, ends, rows = self._bounds()
        grams = gram_hash(range_hash(self._sums(), starts, ends), WINDOW)
        out = np.zeros(self.n, np.int64)
        if len(grams):
            at = np.flatnonzero(rows[: len(grams)] == rows[WINDOW - 1 :])
            keys = mix(grams[at] + rows[at].astype(np.uint64) * GOLDEN)
            order = np.argsort(keys)
            same = keys[order][1:] == keys[order][:-1]
            twice = np.zeros(len(keys), bool)
            twice[order[1:][same]] = True
            twice[order[:-1][same]] = True
            cover = np.zeros(len(rows) + 1, np.int64)
            np.add.at(cover, at[twice], 1)
            np.add.at(cover, at[twice] + WINDOW, -1)
            out = np.bincount(rows[np.cumsum(cover)[:-1] > 0], minlength=self.n)
        return {"n_repeat_words": out} | self.group("words")

    def take(self, keep: np.ndarray) -> Features:
        """The same for some of the texts."""
        sizes = (self.offs[1:] - self.offs[:-1])[keep]
        mask = np.repeat(keep, self.offs[1:] - self.offs[:-1])
        part = Features(self.buf[mask], np.concatenate(([0], np.cumsum(sizes))))
        part._made = {g: {k: v[keep] for k, v in d.items()} for g, d in self._made.items()}
        return part


def cascade(features: Features, rules: tuple[Rule, ...]) -> np.ndarray:
    """Index of the rule that rejects each text, -1 for what stays; rules see only what is left."""
    failed, alive = np.full(features.n, -1), np.arange(features.n)
    for k, rule in enumerate(rules):
        if not len(alive):
            break
        out = rule.rejects(features.group(rule.group))
        failed[alive[out]] = k
        if out.any():
            alive, features = alive[~out], features.take(~out)
    return failed


def order_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES, sample: int = SAMPLE) -> tuple[Rule, ...]:
    """The rules by rejections per second, as measured on at most sample texts drawn by hash of their id."""
    ids = [r.doc_id for r in docs.select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).collect()]
    texts = [r.text for r in docs.where(F.col("doc_id").isin([i for i in ids if i is not None])).select("text").limit(sample).collect()] if ids else []
    if not texts:
        return rules
    buf, offs = texts_of(pa.array(texts, pa.string()))
    worth = {}
    for rule in rules:
        began = time.perf_counter()
        out = rule.rejects(Features(buf, offs).group(rule.group))
        worth[rule.name] = (out.mean() + 1e-4) / max(time.perf_counter() - began, 1e-7)
    return tuple(sorted(rules, key=lambda r: -worth[r.name]))


def quality_report(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """One row for each document with all features, base_failed and kept."""
    ship_package(docs.sparkSession)
    order = order_rules(docs, rules)
    base = {r.name for r in BASE_RULES}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tidy(batches):
            buf, offs = texts_of(b.column(1))
            for i, j in slices(offs):
                f = Features(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
                all_of = f.group("words") | f.group("symbols") | f.group("lines") | f.group("repeats")
                base_failed = np.zeros(j - i, bool)
                for r in rules:
                    if r.name in base:
                        base_failed |= r.rejects(all_of)
                kept = cascade(f, order) < 0
                columns = [pa.array(all_of[k].astype(np.int64)) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), *columns, pa.array(base_failed), pa.array(kept & ~base_failed)], ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean")


def quality_filter(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows of docs that no rule rejects, with all their columns."""
    ship_package(docs.sparkSession)
    order, at = order_rules(docs, rules), docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tidy(batches):
            buf, offs = texts_of(b.column(at))
            kept = [cascade(Features(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i]), order) < 0 for i, j in slices(offs)]
            yield b.filter(pa.array(np.concatenate(kept) if kept else np.zeros(0, bool)))

    return docs.mapInArrow(run, docs.schema)
