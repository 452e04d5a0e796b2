"""Operator 1: token ids of documents in compressed block files with a shared zstandard dictionary.

Format. A folder holds Parquet files of blocks in ascending doc_id order, one file for each range of
ids, and beside it the dictionary. A block row has: range_id, block_id, first_id and last_id, doc_ids, n_tokens of each
document, offsets (byte index of each document's frame in payload, one more than documents), payload
(a zstandard frame for each document of its ids, little-endian unsigned 16-bit where the vocabulary
allows and 32-bit otherwise), width and dict_hash. A short document is read alone: the reader skips all files and row groups
whose first_id and last_id exclude it, and unpacks one frame between two offsets.

Encoding splits a text before every space that a non-space follows, where the byte-level pattern
always splits too, and encodes each distinct part once in each worker.

Cases: null or empty text holds the end id alone; rows with a null doc_id go to the first range and
come first; equal doc_ids are ordered by their ids' bytes; an empty table gives empty files and
an empty dictionary. The dictionary is trained on at most SAMPLE documents: it changes
sizes only, never ids. The documents that a task reads form one block for each BLOCK_TOKENS. Very long texts are one
frame; further columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
import os
import re
import zlib
from collections.abc import Iterator
from functools import reduce
from itertools import islice
from operator import or_

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.session import scratch_path, ship_package

#: The dictionary is trained on ANCHORS runs of RUN ids in a row, each from an id drawn by hash.
ANCHORS, RUN = 16, 32
SAMPLE = ANCHORS * RUN
SAMPLE_TOKENS = 16_384
DICTIONARY_BYTES = 65_536
BLOCK_TOKENS = 1 << 18
RANGE_ROWS = 2_048
QUANTILES = 5_000
KEEP = 64
#: Just below where a dictionary doubles.
TABLE_ENTRIES = 1_390_000
#: A space that doesn't begin a part: white space or the end follows it.
_JOINED = re.compile(r" (?=\s|\Z)")
#: White space other than the space and the line feed.
_ODD = re.compile("[\t\x0b-\r\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
_ASCII_SPACE = "\t\x0b\x0c\r\x1c\x1d\x1e\x1f"
#: Words on which a tokenizer is tried: letters of several scripts and digits at the end.
_PROBES = ("a", "the", "end", "Zürich", "el", "niño", "7", "x2", "été", "конец", "日本", " word", " 42")
_TABLES: dict[str, PartTable] = {}


class PartTable:
    """Distinct parts of texts with their ids as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str, entries: int = TABLE_ENTRIES):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.entries, self.heads, self.tails = entries, {}, {}
        feed = self.tokenizer.encode("\n", add_special_tokens=False).ids
        if len(feed) != 1:
            raise ValueError("a line feed must be a token of its own")
        self.feed, self.feed_bytes = feed[0], np.uint32(feed[0]).tobytes()
        self.stops, self.long = {}, {}
        #: Whether stops and commas behind letters and digits are tokens of their own with this tokenizer.
        self.parted = all(self._whole(w + p) == self._whole(w) + self._whole(p) for w in _PROBES for p in (".", ",", "..", ".,", "...", ",."))

    def _whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint32).tobytes()

    def _learn(self, words: list[str], table: dict[str, bytes], lead: str) -> None:
        """Encodes many words at once, joined by line feeds, which the pattern keeps apart from them."""
        for at in range(0, len(words), 4096):
            some = words[at : at + 4096]
            ids = np.array(self.tokenizer.encode_batch_fast([lead + f"\n{lead}".join(some)], add_special_tokens=False)[0].ids, np.uint32)
            cuts = np.flatnonzero(ids == self.feed)
            if len(cuts) != len(some) - 1:
                table.update((w, self._whole(lead + w)) for w in some)
                continue
            raw, begin = ids.tobytes(), 0
            for w, end in zip(some, [*(4 * cuts).tolist(), 4 * len(ids)], strict=True):
                table[w] = raw[begin:end]
                begin = end + 4

    def learn(self, parts: set[str], heads: set[str]) -> None:
        """Puts parts that follow a space, and heads that don't, into the tables; odd ones are encoded alone."""
        plain, lines = [], []
        for p in parts:
            (lines if "\n" in p else plain).append(p)
        joined = " ".join([*plain, *lines, *heads])
        if "<|" in joined or _ODD.search(joined) or max(map(len, joined.split(" "))) > KEEP:
            odd = {p for p in [*plain, *lines, *heads] if "<|" in p or len(p) > KEEP or _ODD.search(p)}
            self.long = {p: (self._whole(" " + p), self._whole(p)) for p in odd}
            plain, lines, heads = [p for p in plain if p not in odd], [p for p in lines if p not in odd], heads - odd
        split = [(p, p.split("\n"), self.tails) for p in lines] + [(h, h.split("\n"), self.heads) for h in heads]
        for p, x, _ in split:
            if "" in x or " " in p:
                self.long[p] = self._whole(" " + p), self._whole(p)
        split = [x for x in split if x[0] not in self.long]
        firsts = [x[0] for _, x, table in split if table is self.tails]
        rest = [w for _, x, table in split for w in (x[1:] if table is self.tails else x)]
        self._words(plain + firsts, self.tails, " ")
        self._words(rest, self.heads, "")
        for p, x, table in split:
            if len(x) > 1:
                table[p] = self.feed_bytes.join([table[x[0]], *[self.heads[w] for w in x[1:]]])

    def _words(self, parts: list[str], table: dict[str, bytes], lead: str) -> None:
        """Encodes parts without white space: stops and commas behind a letter or digit are tokens of their own, if the tokenizer parts them."""
        words = [p.rstrip(".,") for p in parts]
        words = [w if self.parted and w and (w[-1].isalpha() or w[-1].isdecimal()) else p for p, w in zip(parts, words, strict=True)]
        self._learn([w for w in set(words) if w not in table], table, lead)
        for p, w in zip(parts, words, strict=True):
            if len(p) != len(w):
                table[p] = table[w] + self._stops(p[len(w) :])

    def _stops(self, text: str) -> bytes:
        if text not in self.stops:
            self.stops[text] = self._whole(text) if text else b""
        return self.stops[text]

    def encode_all(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text."""
        if len(self.heads) + len(self.tails) >= self.entries:
            # What came first is what comes often.
            self.tails = dict(islice(self.tails.items(), self.entries // 3))
            self.heads = dict(islice(self.heads.items(), self.entries // 9))
        out, open_, parts, heads = [b""] * len(texts), [], set(), set()
        for k, t in enumerate(texts):
            if not t:
                continue
            head, *rest = self.parts(t)
            first, found = self.heads.get(head) if head else b"", list(map(self.tails.get, rest))
            gaps = []
            if None in found:
                at = found.index(None)
                while at >= 0:
                    gaps.append(at)
                    parts.add(rest[at])
                    try:
                        at = found.index(None, at + 1)
                    except ValueError:
                        at = -1
            if first is None:
                heads.add(head)
            elif not gaps:
                out[k] = first + b"".join(found)
                continue
            open_.append((k, head, first, found, gaps, [rest[i] for i in gaps]))
        if open_:
            self.long = {}
            self.learn(parts, heads)
        for k, head, first, found, gaps, missing in open_:
            for i, p in zip(gaps, missing, strict=True):
                found[i] = self.tails.get(p) or self.long[p][0]
            if first is None:
                first = self.heads.get(head) or self.long[head][1]
            out[k] = first + b"".join(found)
        return out

    def encode(self, text: str | None) -> bytes:
        return self.encode_all([text])[0]

    def parts(self, text: str) -> list[str]:
        """The text cut before each space that a non-space follows."""
        parts = text.split(" ")
        if text.isascii():
            odd = "" in parts or " \n" in text or any(f" {c}" in text for c in _ASCII_SPACE)
        else:
            odd = _JOINED.search(text) is not None
        return self._joined(parts) if odd else parts

    @staticmethod
    def _joined(parts: list[str]) -> list[str]:
        """Puts each part that is empty or begins with white space back to the one before it."""
        out = [[parts[0]]]
        for p in parts[1:]:
            if not p or p[0].isspace():
                out[-1].append(p)
            else:
                out.append([p])
        return [" ".join(x) for x in out]


def part_table(path: str) -> PartTable:
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    if path not in _TABLES:
        _TABLES[path] = PartTable(path)
    return _TABLES[path]


def train_dictionary(docs: DataFrame, tokenizer_path: str, end_id: int, width: int) -> bytes:
    """A dictionary from at most SAMPLE documents of at most SAMPLE_TOKENS ids each; empty if they are too few."""
    ids = [r.doc_id for r in docs.where("doc_id IS NOT NULL").select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(ANCHORS).collect()]
    # Ranges of ids, unlike single ones, let the reader skip pages of a table that is in order.
    near = reduce(or_, [F.col("doc_id").between(i, i + RUN - 1) for i in ids], F.lit(False))
    rows = docs.where(near).orderBy("doc_id", "text").limit(SAMPLE).select("text").collect() if ids else []
    table, kind = part_table(tokenizer_path), np.uint16 if width == 2 else np.uint32
    samples = [np.append(np.frombuffer(table.encode(r.text), np.uint32), end_id)[:SAMPLE_TOKENS].astype(kind).tobytes() for r in rows]
    if len(samples) < 16 or sum(map(len, samples)) < 8 * DICTIONARY_BYTES // 16:
        return b""
    size = min(DICTIONARY_BYTES, sum(map(len, samples)) // 8)
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:  # samples too alike or too small for the trainer
        return b""


def dictionary_hash(dictionary: bytes) -> str:
    return hashlib.sha256(dictionary).hexdigest()


def range_bounds(docs: DataFrame, range_rows: int) -> list[int]:
    """Upper bounds of all ranges but the last, from approximate quantiles of the ids alone.

    A range has about range_rows rows at any size of the table: the bounds that the driver holds are one number for each file.
    """
    n = docs.where("doc_id IS NOT NULL").count()
    wanted = -(-n // range_rows)
    found: list[int] = []
    # One pass for each QUANTILES bounds, as one call of the sketch can't hold them all.
    for at in range(1, wanted, QUANTILES):
        shares = [k / wanted for k in range(at, min(at + QUANTILES, wanted))]
        found += docs.agg(F.percentile_approx("doc_id", shares, min(max(4 * wanted, 4 * QUANTILES), 1 << 20)).alias("q")).first().q or []
    return sorted(set(found))


def write_token_files(docs: DataFrame, path: str, tokenizer_path: str, end_id: int, width: int = 2, range_rows: int = RANGE_ROWS) -> bytes:
    """Writes the block files and the dictionary; gives the dictionary."""
    spark = docs.sparkSession
    ship_package(spark)
    docs = docs.select("doc_id", "text")
    dictionary = train_dictionary(docs, tokenizer_path, end_id, width)
    spark.createDataFrame([(bytearray(dictionary), dictionary_hash(dictionary), width, end_id)], "dictionary binary, dict_hash string, width int, end_id bigint").coalesce(1).write.parquet(f"{path}/dictionary")
    bounds = range_bounds(docs, range_rows)
    kind, label = np.uint16 if width == 2 else np.uint32, dictionary_hash(dictionary)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, given = part_table(tokenizer_path), zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        if width == 2 and max(table.tokenizer.get_vocab_size() - 1, end_id) > 0xFFFF:
            raise ValueError("ids need 32 bits")
        packer, end = zstandard.ZstdCompressor(level=1, dict_data=given), np.uint32(end_id).tobytes()
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part, frames, counts = b.slice(at, 512), [], []
                for own in table.encode_all(part.column(1).to_pylist()):
                    ids = np.frombuffer(own + end, np.uint32)
                    frames.append(packer.compress(ids.astype(kind).tobytes()))
                    counts.append(len(ids))
                keys = part.column(0).fill_null(bounds[0] if bounds else 0).to_numpy(zero_copy_only=False)
                ranges = np.searchsorted(edges, keys, side="left").astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(ranges), part.column(0), pa.array(counts, pa.int64()), pa.array(frames, pa.binary())], ["range_id", "doc_id", "n_tokens", "frame"])

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        state = {"tokens": 0, "block": 0, "before": 0, "range": 0}

        def flush() -> pa.RecordBatch:
            sizes = np.cumsum([0, *(len(x[2]) for x in held)])
            total = int(sum(x[1] for x in held))
            row = {
                "range_id": [state["range"]], "block_id": [state["block"]], "tokens_before": [state["before"]], "tokens": [total], "first_id": [min((x[0] for x in held if x[0] is not None), default=None)], "last_id": [max((x[0] for x in held if x[0] is not None), default=None)], "doc_ids": [[x[0] for x in held]], "n_tokens": [[x[1] for x in held]],
                "offsets": [sizes.tolist()], "payload": [b"".join(x[2] for x in held)], "width": [width], "dict_hash": [label],
            }
            state.update(block=state["block"] + 1, before=state["before"] + total, tokens=0)
            held.clear()
            return pa.RecordBatch.from_pydict(row, schema=pa.schema([("range_id", pa.int32()), ("block_id", pa.int32()), ("tokens_before", pa.int64()), ("tokens", pa.int64()), ("first_id", pa.int64()), ("last_id", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("n_tokens", pa.list_(pa.int64())), ("offsets", pa.list_(pa.int64())), ("payload", pa.binary()), ("width", pa.int32()), ("dict_hash", pa.string())]))

        for b in batches:
            for r, d, n, f in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                state["range"] = r
                held.append((d, n, f))
                state["tokens"] += n
                if state["tokens"] >= BLOCK_TOKENS:
                    yield flush()
        if held:
            yield flush()

    edges = np.array(bounds, np.int64)
    frames = docs.mapInArrow(encode, "range_id int, doc_id bigint, n_tokens bigint, frame binary")
    dealt = frames.repartitionById(len(bounds) + 1, F.col("range_id"))
    packed = dealt.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "frame").mapInArrow(blocks, "range_id int, block_id int, tokens_before bigint, tokens bigint, first_id bigint, last_id bigint, doc_ids array<bigint>, n_tokens array<bigint>, offsets array<bigint>, payload binary, width int, dict_hash string")
    packed.write.option("compression", "none").parquet(f"{path}/blocks")
    return dictionary


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """One row (doc_id, start, ids) for each document; start counts the ids of all documents before it."""
    return _read(spark, path, "ids array<int>", lambda ids: np.asarray(ids, np.int32), pa.list_(pa.int32()))


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """One row (doc_id, start, n_tokens, ids_crc32) for each document, all from the files."""
    return _read(spark, path, "ids_crc32 bigint", lambda ids: zlib.crc32(ids.astype("<u4").tobytes()), pa.int64())


def _blocks_with(spark: SparkSession, path: str, doc_id: int) -> DataFrame:
    """The blocks whose range of ids holds doc_id: the bounds go down to the statistics of the files."""
    return spark.read.parquet(f"{path}/blocks").where((F.col("first_id") <= doc_id) & (F.col("last_id") >= doc_id))


def read_one(spark: SparkSession, path: str, doc_id: int) -> np.ndarray | None:
    """The ids of one document: only blocks that can hold it are read, and only its frame is unpacked. Of equal doc_ids it is the first."""
    meta = spark.read.parquet(f"{path}/dictionary").first()
    at = F.array_position("doc_ids", F.lit(doc_id)).cast("int")
    found = _blocks_with(spark, path, doc_id).select("range_id", "block_id", "offsets", "payload", "width", at.alias("p")).where("p > 0")
    frame = F.expr("substring(payload, int(offsets[p - 1]) + 1, int(offsets[p] - offsets[p - 1]))")
    row = found.orderBy("range_id", "block_id").select(frame.alias("frame"), "width").first()
    if row is None:
        return None
    given = zstandard.ZstdCompressionDict(bytes(meta.dictionary)) if meta.dictionary else None
    raw = zstandard.ZstdDecompressor(dict_data=given).decompress(bytes(row.frame))
    return np.frombuffer(raw, np.uint16 if row.width == 2 else np.uint32).astype(np.uint32)


def _read(spark: SparkSession, path: str, column: str, made, kind: pa.DataType) -> DataFrame:
    ship_package(spark)
    meta = spark.read.parquet(f"{path}/dictionary").first()
    dictionary, label = bytes(meta.dictionary), meta.dict_hash
    if dictionary_hash(dictionary) != label:
        raise ValueError("the dictionary doesn't match its hash")
    rows = spark.read.parquet(f"{path}/blocks")
    totals = {r.range_id: r.n for r in rows.groupBy("range_id").agg(F.sum("tokens").alias("n")).collect()}  # one for each file
    before, start = 0, {}
    for k in sorted(totals):
        start[k], before = before, before + totals[k]
    name, schema_name = column.split(" ")[0], column

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        given = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        reader = zstandard.ZstdDecompressor(dict_data=given)
        for b in batches:
            for i in range(b.num_rows):
                row = {f: b.column(f)[i].as_py() for f in b.schema.names}
                if row["dict_hash"] != label:
                    raise ValueError("a block names another dictionary")
                kind_of = np.uint16 if row["width"] == 2 else np.uint32
                o, view = row["offsets"], memoryview(row["payload"])
                values = [made(np.frombuffer(reader.decompress(view[o[j] : o[j + 1]]), kind_of)) for j in range(len(o) - 1)]
                counts = np.array(row["n_tokens"], np.int64)
                starts = start[row["range_id"]] + row["tokens_before"] + np.concatenate(([0], np.cumsum(counts)[:-1]))
                yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(starts, pa.int64()), pa.array(counts), pa.array(values, kind)], ["doc_id", "start", "n_tokens", name])

    return rows.select("range_id", "tokens_before", "doc_ids", "n_tokens", "offsets", "payload", "width", "dict_hash").mapInArrow(unpack, f"doc_id bigint, start bigint, n_tokens bigint, {schema_name}")


def token_files_of(docs: DataFrame, tokenizer_path: str, end_id: int = 2) -> DataFrame:
    """Writes the files of docs in the shared folder and gives the digests that they hold."""
    spark = docs.sparkSession
    path = scratch_path(spark, "token-files")
    write_token_files(docs, path, tokenizer_path, end_id)
    return read_digests(spark, path)
