"""Operator 3: removal of repeated byte strings by a depth-limited radix sort of suffixes.

The suffixes of a text are its windows of THRESHOLD bytes; two of them fall into one group exactly if
the windows are equal. The radix passes go from the most significant digit on, and each carries on
only groups of two or more:

1. the first digit of a window is its anchor: the place inside it whose ANCHOR bytes hash lowest, leftmost
   among equals. Equal windows have equal anchors at equal places, and one anchor stands for all the
   windows in a row that choose it, so a corpus has about one anchor for 160 bytes;
2. where two anchors agree in all the bytes that their windows cover, all these windows are repeated and need no more passes;
3. what agrees in pass 1 and not in pass 2 lies at the border of a repeated passage: there one anchor for
   each value of pass 2 is opened into its windows, which are sorted within their anchor by their bytes in digits of
   ANCHOR bytes, the most significant first. Ranks that one window alone has are dropped after each digit; what
   is left at THRESHOLD bytes are exactly the repeated windows.

Groups are counted by partial aggregates, and rows meet the counts of a hot digit, such as a passage that a third of all
rows share, where they lie (operators/skew.py). An anchor with very many kinds is split by its windows.
Hashes have 64 bits for each digit and windows are compared under the hash of their anchor too.

Cases: null text counts as empty; texts shorter than THRESHOLD keep all bytes; copies and repeated rows of at
least THRESHOLD bytes lose every byte, as each also lies in the other; rows with equal doc_id and different
text are told apart by the hash of their text; an empty table gives no rows; further columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.common import GOLDEN, mix, prefix_hash, range_hash, slices, texts_of
from neardup.operators.skew import join_counted, repeated
from neardup.session import materialize, release, ship_package

THRESHOLD = 400
ANCHOR = 80


def sliding_argmin(values: np.ndarray, width: int) -> np.ndarray:
    """Index of the lowest of each width values in a row, by their upper 32 bits, leftmost among equals."""
    n = len(values) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    packed = (values & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(values), dtype=np.uint64)
    full = -(-len(packed) // width) * width
    blocks = np.concatenate((packed, np.full(full - len(packed), np.uint64(0xFFFFFFFFFFFFFFFF)))).reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, 1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], 1)[:, ::-1].ravel()
    low = np.minimum(behind[:n], ahead[width - 1 : width - 1 + n])
    return (low & np.uint64(0xFFFFFFFF)).astype(np.int64)


def anchors_of(buf: np.ndarray, offs: np.ndarray, threshold: int = THRESHOLD, anchor: int = ANCHOR) -> dict[str, np.ndarray]:
    """Anchors of all windows: row, first and last window start (in the row), digits of passes 1 and 2."""
    none = np.zeros(0, np.int64)
    if len(buf) < threshold:
        return {"row": none, "lo": none, "hi": none, "h": none, "c": none}
    sums = prefix_hash(buf)
    starts = np.arange(len(buf) - anchor + 1)
    grams = range_hash(sums, starts, starts + anchor)
    low = sliding_argmin(grams, threshold - anchor + 1)
    last = np.repeat(offs[1:], offs[1:] - offs[:-1])[: len(low)] - threshold
    s = np.flatnonzero(np.arange(len(low)) <= last)
    if not len(s):
        return {"row": none, "lo": none, "hi": none, "h": none, "c": none}
    m = low[s]
    first = np.concatenate(([True], (m[1:] != m[:-1]) | (s[1:] != s[:-1] + 1)))
    at = np.flatnonzero(first)
    lo, hi, m = s[at], s[np.concatenate((at[1:], [len(s)])) - 1], m[at]
    row = np.searchsorted(offs, lo, side="right") - 1
    context = mix(range_hash(sums, lo, hi + threshold) + (m - lo).astype(np.uint64) * GOLDEN)
    return {"row": row, "lo": lo - offs[row], "hi": hi - offs[row], "h": grams[m].view(np.int64), "c": context.view(np.int64)}


def _keyed(docs: DataFrame) -> DataFrame:
    ship_package(docs.sparkSession)
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select("doc_id", F.xxhash64(text).alias("t"), text.alias("text"))


def _anchors(keyed: DataFrame, threshold: int, anchor: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            buf, offs = texts_of(b.column(2))
            for i, j in slices(offs):
                a = anchors_of(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i], threshold, anchor)
                rows = pa.array(a["row"] + i)
                yield pa.RecordBatch.from_arrays([b.column(0).take(rows), b.column(1).take(rows), pa.array(a["lo"].astype(np.int32)), pa.array(a["hi"].astype(np.int32)), pa.array(a["h"]), pa.array(a["c"])], ["doc_id", "t", "lo", "hi", "h", "c"])

    return keyed.where(F.octet_length("text") >= threshold).mapInArrow(run, "doc_id bigint, t bigint, lo int, hi int, h bigint, c bigint")


def _in_text(opened: DataFrame, keyed: DataFrame, threshold: int) -> DataFrame:
    """Adds to each opened anchor the bytes that its windows cover."""
    per_doc = opened.groupBy("doc_id", "t").agg(F.collect_list(F.struct("lo", "hi", "h")).alias("open"))
    both = keyed.alias("k").join(per_doc.alias("p"), F.col("k.doc_id").eqNullSafe(F.col("p.doc_id")) & (F.col("k.t") == F.col("p.t")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for k in range(b.num_rows):
                raw = b.column("text")[k].as_py().encode()
                own = (b.column("doc_id")[k].as_py(), b.column("t")[k].as_py())
                rows += [(x["h"], *own, x["lo"], x["hi"], raw[x["lo"] : x["hi"] + threshold]) for x in b.column("open")[k].as_py()]
                if len(rows) > 4096 or k == b.num_rows - 1:
                    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*rows, strict=True), kinds, strict=True)], ["h", "doc_id", "t", "lo", "hi", "bytes"])
                    rows = []

    return both.select("k.doc_id", "k.t", "text", "open").mapInArrow(run, "h bigint, doc_id bigint, t bigint, lo int, hi int, bytes binary")


def _windows(raw: list[bytes], threshold: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Running hash sums of covered bytes put together, and the start, row and place of each of their windows."""
    sizes = np.array([len(x) for x in raw], np.int64)
    counts, begin = sizes - threshold + 1, np.concatenate(([0], np.cumsum(sizes)[:-1]))
    row = np.repeat(np.arange(len(raw)), counts)
    place = np.arange(len(row)) - np.repeat(np.concatenate(([0], np.cumsum(counts)[:-1])), counts)
    return prefix_hash(np.frombuffer(b"".join(raw), np.uint8)), begin[row] + place, row, place


def window_keys(raw: list[bytes], h: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all windows of covered bytes under their anchors' hashes, with the row and place of each."""
    sums, s, row, place = _windows(raw, threshold)
    return mix(range_hash(sums, s, s + threshold) ^ h.view(np.uint64)[row]), row, place


def radix_sorted(sums: np.ndarray, starts: np.ndarray, group: np.ndarray, threshold: int, digit: int) -> tuple[np.ndarray, np.ndarray]:
    """Windows that occur more than once in their group, in order of (group, digits), and the rank of each one's content.

    Most significant digit first: a pass sorts what is left by (rank so far, next digit bytes), and only
    ranks that two windows or more share go on. Digits are in the order of their hashes. Depth ends at threshold bytes.
    """
    alive, rank = np.arange(len(starts)), group
    for depth in range(0, threshold, digit):
        s = starts[alive]
        key = range_hash(sums, s + depth, s + min(depth + digit, threshold))
        order = np.lexsort((key, rank))
        key, before = key[order], rank[order]
        new = np.concatenate(([0], np.cumsum((before[1:] != before[:-1]) | (key[1:] != key[:-1])))) if len(order) else np.zeros(0, np.int64)
        shared = np.bincount(new)[new] > 1 if len(order) else np.zeros(0, bool)
        alive, rank = alive[order][shared], new[shared]
    return alive, rank


def _runs(row: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, first and last place of each run of windows that follow each other in a row; both come sorted."""
    if not len(row):
        return row, place, place
    cut = np.flatnonzero((row[1:] != row[:-1]) | (place[1:] != place[:-1] + 1)) + 1
    first, last = np.concatenate(([0], cut)), np.concatenate((cut, [len(row)])) - 1
    return row[first], place[first], place[last]


def _third_pass(covered: DataFrame, threshold: int, anchor: int, group_rows: int = 512) -> DataFrame:
    """Runs (doc_id, t, lo, hi) of repeated windows; rows of covered come together by h."""

    def settle(rows: list[tuple]) -> pa.RecordBatch:
        sums, s, row, place = _windows([r[5] for r in rows], threshold)
        found, _ = radix_sorted(sums, s, np.array([r[0] for r in rows], np.int64)[row], threshold, anchor)
        found.sort()
        at, first, last = _runs(row[found], place[found])
        pick = [rows[i] for i in at.tolist()]
        lo = np.array([r[3] for r in pick], np.int64)
        return pa.RecordBatch.from_arrays([pa.array([r[1] for r in pick], pa.int64()), pa.array([r[2] for r in pick], pa.int64()), pa.array((lo + first).astype(np.int32)), pa.array((lo + last).astype(np.int32))], ["doc_id", "t", "lo", "hi"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for b in batches:
            for r in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if len(held) >= group_rows and r[0] != held[-1][0]:
                    yield settle(held)
                    held = []
                held.append(r)
        if held:
            yield settle(held)

    return covered.repartition("h").sortWithinPartitions("h").mapInArrow(run, "doc_id bigint, t bigint, lo int, hi int")


def _third_pass_hot(covered: DataFrame, threshold: int) -> DataFrame:
    """The same for anchors of very many kinds, window by window: no group comes together in a task."""

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                p = b.slice(at, 256)
                keys, row, place = window_keys(p.column("bytes").to_pylist(), p.column("h").to_numpy(), threshold)
                rows = pa.array(row)
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), p.column("doc_id").take(rows), p.column("t").take(rows), pa.array((p.column("lo").to_numpy()[row] + place).astype(np.int32))], ["w", "doc_id", "t", "s"])

    windows = materialize(covered.mapInArrow(explode, "w bigint, doc_id bigint, t bigint, s int"), "hot-windows")
    return repeated(windows, ["w"]).select("doc_id", "t", F.col("s").alias("lo"), F.col("s").alias("hi"))


#: An anchor with more kinds of covered bytes than this is settled window by window.
HOT_KINDS = 4_096


def repeated_spans(docs: DataFrame, threshold: int = THRESHOLD, anchor: int = ANCHOR, hot_kinds: int = HOT_KINDS) -> tuple[DataFrame, DataFrame]:
    """The keyed texts, and rows (doc_id, t, lo, hi): all windows that start from lo to hi occur elsewhere too."""
    keyed = _keyed(docs)
    first = materialize(_anchors(keyed, threshold, anchor), "anchors")
    second = materialize(repeated(first, ["h"]), "twice-anchored")
    release(first)
    kinds = second.groupBy("h", "c").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "t", "lo", "hi")).alias("one"))
    kinds = materialize(kinds, "kinds")
    whole = join_counted(second, kinds.where("n > 1"), ["h", "c"], "left_semi").select("doc_id", "t", "lo", "hi")
    several = materialize(kinds.groupBy("h").agg(F.count("*").alias("k")).where("k > 1"), "several-kinds")
    opened = join_counted(kinds, several, ["h"], n="k").select("h", "k", "one.*")
    counts = several.agg(F.max("k").alias("most")).first().most or 0
    spans = whole
    hot = F.col("k") > hot_kinds
    spans = spans.unionByName(_third_pass(_in_text(opened.where(~hot), keyed, threshold), threshold, anchor))
    if counts > hot_kinds:
        spans = spans.unionByName(_third_pass_hot(_in_text(opened.where(hot), keyed, threshold), threshold))
    return keyed, spans


def merged(spans: np.ndarray, threshold: int) -> np.ndarray:
    """Maximal covered byte ranges from (lo, hi) runs of window starts."""
    if not len(spans):
        return np.zeros((0, 2), np.int64)
    spans = spans[np.argsort(spans[:, 0], kind="stable")]
    ends = np.maximum.accumulate(spans[:, 1] + threshold)
    cut = np.flatnonzero(spans[1:, 0] > ends[:-1]) + 1
    return np.column_stack((spans[np.concatenate(([0], cut)), 0], ends[np.concatenate((cut, [len(ends)])) - 1]))


def _per_document(docs: DataFrame, threshold: int, anchor: int, hot_kinds: int) -> DataFrame:
    keyed, spans = repeated_spans(docs, threshold, anchor, hot_kinds)
    lists = spans.groupBy("doc_id", "t").agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    joined = keyed.alias("k").join(lists.alias("s"), F.col("k.doc_id").eqNullSafe(F.col("s.doc_id")) & (F.col("k.t") == F.col("s.t")), "left")
    return joined.select("k.doc_id", "k.text", F.col("s.spans.lo").alias("lo"), F.col("s.spans.hi").alias("hi"))


def _kept(text: str, lo: list[int] | None, hi: list[int] | None, threshold: int) -> tuple[bytes, bytes, np.ndarray]:
    raw = text.encode()
    gone = merged(np.column_stack((lo, hi)), threshold) if lo else np.zeros((0, 2), np.int64)
    edges = [0, *gone.ravel().tolist(), len(raw)]
    return raw, b"".join(raw[edges[i] : edges[i + 1]] for i in range(0, len(edges), 2)), gone


def removal_digests(docs: DataFrame, threshold: int = THRESHOLD, anchor: int = ANCHOR, hot_kinds: int = HOT_KINDS) -> DataFrame:
    """One row (doc_id, n_bytes, n_removed, n_spans, kept_sha256) for each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for k in range(b.num_rows):
                raw, kept, gone = _kept(*(b.column(i)[k].as_py() for i in (1, 2, 3)), threshold)
                out.append((len(raw), len(raw) - len(kept), len(gone), hashlib.sha256(kept).hexdigest()))
            columns = list(zip(*out, strict=True)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(columns[i], pa.int64()) for i in range(3)), pa.array(columns[3], pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return _per_document(docs, threshold, anchor, hot_kinds).mapInArrow(run, "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")


def remove_repeats(docs: DataFrame, threshold: int = THRESHOLD, anchor: int = ANCHOR, hot_kinds: int = HOT_KINDS) -> DataFrame:
    """One row (doc_id, kept binary, spans) for each document; kept may be cut inside a character."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = [_kept(*(b.column(i)[k].as_py() for i in (1, 2, 3)), threshold) for k in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([m[1] for m in made], pa.binary()), pa.array([m[2].tolist() for m in made], pa.list_(pa.list_(pa.int64())))], ["doc_id", "kept", "spans"])

    return _per_document(docs, threshold, anchor, hot_kinds).mapInArrow(run, "doc_id bigint, kept binary, spans array<array<bigint>>")
