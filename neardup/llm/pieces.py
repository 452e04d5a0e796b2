"""Operator 9: SentencePiece encoding and decoding by a table of distinct marked words.

In a model whose pieces never hold the marker after another character, no merge crosses the place
before a marker. Each marked word of a text is therefore segmented on its own, and the ids of a text are those of its words in
order:

1. every distinct word of all documents is counted, by partial counts of each task;
2. the most frequent ones, HEAD at most by a threshold on their counts, are segmented once each: the table has their ids and
   decoded form, and its size is bounded at any size of the corpus, so it is sent to all tasks;
3. a document's words are looked up in order. Words beyond the table are segmented where they occur, once for each table
   of a task, which starts anew from the shared one when it is full.

Joining the rare words back through a shuffle would be the other way for step 3; README.md says what it would move.

Cases: null or empty text has the begin and end ids alone; runs of spaces, leading and trailing
spaces and the marker character itself behave as in the library; words longer than KEEP characters
are segmented but not kept. Rows map one to one, so repeated or null doc_ids stay as they are; an empty table gives no rows; further
columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.common import tidy
from neardup.session import materialize, release, ship_package

MARK = "▁"
KEEP = 64
#: Most words of the shared table, and of what a task adds to it before it starts anew.
HEAD = 200_000
TABLE_ENTRIES = 200_000
_TABLES: dict[str, PieceTable] = {}


def can_split(model: sentencepiece.SentencePieceProcessor) -> bool:
    """True if no piece of the model has the marker after another character."""
    return not any(MARK in model.id_to_piece(i).lstrip(MARK) for i in range(model.get_piece_size()))


class PieceTable:
    """Distinct marked words with their ids (little-endian unsigned 32-bit) and decoded text."""

    def __init__(self, model_path: str, entries: int = TABLE_ENTRIES):
        self.model = sentencepiece.SentencePieceProcessor(model_file=model_path)
        if not can_split(self.model):
            raise ValueError("pieces of this model can cross word markers")
        self.entries, self.shared, self.table = entries, {}, {}
        self.begin = self.model.bos_id().to_bytes(4, "little")
        self.end = self.model.eos_id().to_bytes(4, "little")
        self.lone = (self.model.piece_to_id(MARK).to_bytes(4, "little"), "")

    def start(self, shared: dict[str, tuple[bytes, str]]) -> PieceTable:
        """From now on with these words and no others."""
        self.shared, self.table = shared, dict(shared)
        return self

    def segment(self, word: str) -> tuple[bytes, str]:
        """Ids and decoded text of a marked word."""
        ids = self.model.encode(word)
        return b"".join(i.to_bytes(4, "little") for i in ids), self.model.decode(ids)

    def add(self, word: str) -> tuple[bytes, str]:
        found = self.segment(word)
        if len(word) <= KEEP:
            if len(self.table) >= self.entries + len(self.shared):
                self.table = dict(self.shared)
            self.table[word] = found
        return found

    def words(self, text: str) -> tuple[list[str], list[tuple[bytes, str]]]:
        """The marked words of a text in order, and what a space at its end adds."""
        words = text.replace(MARK, " ").split(" ")
        return self._with_runs(words) if "" in words else (words, [])

    def encode(self, text: str | None) -> tuple[bytes, str]:
        """All ids of a text with begin and end, and what the library decodes them to."""
        if not text:
            return self.begin + self.end, ""
        words, tail = self.words(text)
        get = self.table.get
        found = [get(w) or self.add(w) for w in words] + tail
        return self.begin + b"".join([x[0] for x in found]) + self.end, " ".join([x[1] for x in found])

    def _with_runs(self, words: list[str]) -> tuple[list[str], list[tuple[bytes, str]]]:
        """Joins the empty parts that runs of spaces leave to the word behind them."""
        out, run = [], 0
        for w in words:
            if w:
                out.append(" " * run + w)
                run = 0
            else:
                run += 1
        if not run:
            return out, []
        if run == 1:
            return out, [self.lone]
        return [*out, " " * (run - 1)], []


def piece_table(model_path: str) -> PieceTable:
    """The table of this worker for a model."""
    if model_path not in _TABLES:
        _TABLES[model_path] = PieceTable(model_path)
    return _TABLES[model_path]


def word_counts(texts: DataFrame, model_path: str) -> DataFrame:
    """(word, n) of all distinct marked words of texts (text) with KEEP characters at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, counts = piece_table(model_path), Counter()

        def batch() -> pa.RecordBatch:
            rows = [(w, n) for w, n in counts.items() if len(w) <= KEEP]
            counts.clear()
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int64())], ["word", "n"])

        for b in tidy(batches):
            for t in b.column(0):
                if t := t.as_py():
                    counts.update(table.words(t)[0])
                if len(counts) > 2 * TABLE_ENTRIES:
                    yield batch()
        yield batch()

    return texts.mapInArrow(run, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n"))


def frequent_words(counts: DataFrame, most: int = HEAD) -> DataFrame:
    """(word) of the words whose count reaches the least threshold, in steps of a quarter of a doubling, that no more than most reach."""
    step = F.floor(4 * F.log2("n")).cast("int")
    sizes = counts.groupBy(step.alias("step")).agg(F.count("*").alias("words")).collect()  # a row for each quarter of a doubling
    least, total = None, 0
    for r in sorted(sizes, key=lambda r: -r.step):
        total += r.words
        if total > most:
            break
        least = r.step
    return counts.where(step >= least).select("word") if least is not None else counts.where("false").select("word")


def shared_table(texts: DataFrame, model_path: str, most: int = HEAD) -> dict[str, tuple[bytes, str]]:
    """The frequent words of texts with their ids and decoded text, each segmented once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = piece_table(model_path)
        for b in tidy(batches):
            made = [table.segment(w) for w in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x for x, _ in made], pa.binary()), pa.array([d for _, d in made], pa.string())], ["word", "ids", "decoded"])

    counts = materialize(word_counts(texts, model_path), "distinct-words")
    found = frequent_words(counts, most).mapInArrow(run, "word string, ids binary, decoded string").toArrow()  # at most HEAD rows
    release(counts)
    return {w: (i, d) for w, i, d in zip(*(found.column(k).to_pylist() for k in range(3)), strict=True)}


def _encoded(docs: DataFrame, model_path: str, made, schema: str) -> DataFrame:
    """made(slice of a batch, its encoded texts) for all rows of docs (id, text), with the table of their words."""
    spark = docs.sparkSession
    ship_package(spark)
    table_of = spark.sparkContext.broadcast(shared_table(docs.select(docs.columns[1]), model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = piece_table(model_path).start(table_of.value)
        for b in tidy(batches):
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                yield made(part, [table.encode(t.as_py()) for t in part.column(1)])
        table.start({})

    return docs.mapInArrow(run, schema)


def encode_documents(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row (id, ids array<int>, decoded string) for each input row."""

    def made(part: pa.RecordBatch, rows: list[tuple[bytes, str]]) -> pa.RecordBatch:
        import numpy as np

        ids = pa.array([np.frombuffer(x, np.int32) for x, _ in rows], pa.list_(pa.int32()))
        return pa.RecordBatch.from_arrays([part.column(0), ids, pa.array([d for _, d in rows], pa.string())], ["id", "ids", "decoded"])

    kind = docs.schema[id_col].dataType.simpleString()
    return _encoded(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), model_path, made, f"id {kind}, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, model_path: str) -> DataFrame:
    """One row (doc_id, n_tokens, ids_sha256, decoded_sha256) for each row of docs (doc_id, text)."""

    def made(part: pa.RecordBatch, rows: list[tuple[bytes, str]]) -> pa.RecordBatch:
        counts = pa.array([len(ids) // 4 for ids, _ in rows], pa.int64())
        sums = [pa.array([hashlib.sha256(x).hexdigest() for x in column], pa.string()) for column in ([ids for ids, _ in rows], [d.encode() for _, d in rows])]
        return pa.RecordBatch.from_arrays([part.column(0), counts, *sums], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return _encoded(docs.select("doc_id", "text"), model_path, made, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
