"""Operator 10: benchmark decontamination by SimHash of item-sized windows and a multi-index of Hamming blocks.

For each size that benchmark items have, windows of so many shingles are taken from a document; a window's 64-bit
SimHash goes to an index that holds the items' fingerprints in BLOCKS blocks of bits: two fingerprints within RADIUS
are within RADIUS // BLOCKS in one block at least, so the index finds all items within the radius. These are the candidates, and
one counts if the weighted Jaccard similarity of its 5-word shingles (weights are occurrences) is 0.8 or more.

Which items a window is like is for the fingerprints alone to tell. Only windows that no item at all can pass for want of
shared shingles get no fingerprint: a window needs 8/9 of its shingles among those of all items together, which a table
of these tells for all places of a document at once. This leaves out no window that the full comparison would accept.

Two bags with a similarity of exactly 0.8 differ in 9.7 of 64 bits on average, so RADIUS 20 misses about three in ten thousand of
them, and fewer above. At such a distance blocks can't be very selective: see README.md for figures.

Words are runs of characters other than space and 0x09-0x0D, with A-Z lowered. Cases: null or empty texts and items match nothing;
an item or document of fewer than 5 words is one shingle; a document shorter than an item is one window; repeated rows and
items are reported each; null ids are passed on; no items or no documents give no rows; further columns of documents, whatever
their names, are handed on by without_benchmark() and not read by contaminated(). Items are sent
to the tasks in groups of at most ITEM_BYTES, one pass over the documents for each group.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.common import LOWER, mix, shingle_rows, slices, texts_of, tidy
from neardup.session import ship_package

RADIUS, BLOCKS = 20, 4
ITEM_BYTES = 16 << 20
_BITS = np.arange(64, dtype=np.uint64)


def simhash(hashes: np.ndarray) -> int:
    """Majority of each bit over the shingles with their occurrences; a tie gives 0."""
    votes = ((mix(hashes)[:, None] >> _BITS) & np.uint64(1)).sum(0, dtype=np.int64)
    return int(((2 * votes > len(hashes)).astype(np.uint64) << _BITS).sum(dtype=np.uint64))


#: Votes of so many places at most are held at once.
REACH = 1 << 14


class Prints:
    """Fingerprints of the windows of one document, from running sums of the votes of its shingles; each is what simhash() gives."""

    def __init__(self, bag: np.ndarray, longest: int, last: int):
        """longest: of all windows; last: the last place that a window may end at."""
        self.bag, self.longest, self.last = bag, longest, min(last, len(bag))
        self.low, self.sums = 0, np.zeros((1, 64), np.int32)

    def of(self, starts: np.ndarray, size: int) -> np.ndarray:
        """starts in rising order."""
        out = []
        while len(starts):
            at = int(starts[0])
            if at < self.low or at + size > self.low + len(self.sums) - 1:
                self.low = max(0, at - self.longest)
                own = self.bag[self.low : max(at + size, min(self.last, self.low + REACH))]
                self.sums = np.zeros((len(own) + 1, 64), np.int32)
                np.cumsum((mix(own)[:, None] >> _BITS) & np.uint64(1), axis=0, out=self.sums[1:])
            held = int(np.searchsorted(starts, self.low + len(self.sums) - 1 - size, side="right"))
            x, starts = starts[:held] - self.low, starts[held:]
            votes = self.sums[x + size] - self.sums[x]
            out.append(np.packbits(2 * votes > size, axis=1, bitorder="little").view("<u8").ravel().astype(np.uint64))
        return np.concatenate(out)


class HammingIndex:
    """All fingerprints within a radius, by blocks of bits that are looked up within radius // blocks."""

    def __init__(self, prints: list[int], radius: int = RADIUS, blocks: int = BLOCKS):
        self.prints, self.radius, self.block_radius = np.array(prints, np.uint64), radius, radius // blocks
        edges = [64 * k // blocks for k in range(blocks + 1)]
        self.blocks = [(lo, (1 << (hi - lo)) - 1) for lo, hi in zip(edges, edges[1:], strict=False)]
        self.values = [((self.prints >> np.uint64(lo)) & np.uint64(mask)).astype(np.uint32) for lo, mask in self.blocks]
        #: For each block the prints near a value of it, made when the value is first asked for: at most a table of all values.
        self.tables: list[dict[int, np.ndarray]] = [{} for _ in self.blocks]
        self.held = 0

    def candidates(self, print_: int) -> np.ndarray:
        """The prints that a block brings up."""
        found = []
        for (lo, mask), values, table in zip(self.blocks, self.values, self.tables, strict=True):
            found.append(self._near_value(values, table, (print_ >> lo) & mask))
        return np.unique(np.concatenate(found))

    def _near_value(self, values: np.ndarray, table: dict[int, np.ndarray], own: int) -> np.ndarray:
        if own not in table:
            if self.held > MOST_HELD:
                for t in self.tables:
                    t.clear()
                self.held = 0
            table[own] = np.flatnonzero(np.bitwise_count(values ^ np.uint32(own)) <= self.block_radius)
            self.held += len(table[own])
        return table[own]

    def near_all(self, prints: np.ndarray, only: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(k, i): print k of many and index print i within the radius, in order; of index prints those where only is True."""
        own, back = np.unique(prints, return_inverse=True)
        step, ks, found = max(1, AT_ONCE // max(1, len(self.prints))), [], []
        for a in range(0, len(own), step):
            some = own[a : a + step]
            hit = np.zeros((len(some), len(self.prints)), bool)
            for (lo, mask), values, table in zip(self.blocks, self.values, self.tables, strict=True):
                for r, v in enumerate(((some >> np.uint64(lo)) & np.uint64(mask)).tolist()):
                    hit[r, self._near_value(values, table, v)] = True
            k, i = np.nonzero(hit & only)
            within = np.bitwise_count(self.prints[i] ^ some[k]) <= self.radius
            ks.append(k[within] + a)
            found.append(i[within])
        k, i = np.concatenate(ks), np.concatenate(found)
        # Each print stands for all windows that have it.
        begin, n = np.searchsorted(k, back), np.searchsorted(k, back, side="right")
        n -= begin
        rows = np.repeat(begin - (np.cumsum(n) - n), n) + np.arange(n.sum())
        return np.repeat(np.arange(len(prints)), n), i[rows]

    def near(self, print_: int) -> list[int]:
        """The prints within the radius."""
        found = self.candidates(print_)
        return found[np.bitwise_count(self.prints[found] ^ np.uint64(print_)) <= self.radius].tolist()


#: Entries of an index's tables, and print pairs that are looked at together.
MOST_HELD, AT_ONCE = 1 << 24, 1 << 22


def weighted_jaccard(a: np.ndarray, b: np.ndarray) -> tuple[int, int]:
    """Shared and total weight of two bags of shingles."""
    x, nx = np.unique(a, return_counts=True)
    y, ny = np.unique(b, return_counts=True)
    _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
    shared = int(np.minimum(nx[i], ny[j]).sum())
    return shared, len(a) + len(b) - shared


class Items:
    """Shingles and fingerprints of benchmark items."""

    def __init__(self, ids: list, texts: list[str | None]):
        buf, offs = texts_of(pa.array(texts, pa.string()))
        hashes, at = shingle_rows(LOWER[buf], offs)
        keep = [k for k in range(len(ids)) if at[k + 1] > at[k]]
        self.ids = [ids[k] for k in keep]
        self.bags = [hashes[at[k] : at[k + 1]] for k in keep]
        self.index = HammingIndex([simhash(b) for b in self.bags])
        self.keys = np.unique(np.concatenate([np.zeros(0, np.uint64), *self.bags]))
        self.sizes = np.array([len(b) for b in self.bags], np.int64)
        self.lengths, self.longest = np.unique(self.sizes), int(self.sizes.max(initial=0))
        self.needs: dict[int, tuple[list[int], list[int]]] = {}
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[(self.keys & np.uint64((1 << 20) - 1)).astype(np.int64)] = True

    def places(self, hashes: np.ndarray) -> np.ndarray:
        """Where a shingle of any item stands."""
        p = np.flatnonzero(self.maybe[(hashes & np.uint64((1 << 20) - 1)).astype(np.int64)])
        if not len(p):
            return p
        k = np.minimum(np.searchsorted(self.keys, hashes[p]), len(self.keys) - 1)
        return p[self.keys[k] == hashes[p]]

    def windows(self, n: int, p: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """(size, starts) of the item-sized windows of a document of n shingles that some item may be like; p as from places."""
        for size, least in zip(*self._needs(min(n, self.longest)), strict=True):
            if least > len(p):
                continue
            # Some window holds so many places only if so many of them in a row lie within a window's length.
            near = np.flatnonzero(p[least - 1 :] - p[: len(p) - least + 1] < size)
            if not len(near):
                continue
            first, last = int(p[near[0] + least - 1]) - size + 1, int(p[near[-1]])
            starts = np.arange(max(0, first), min(last, n - size) + 1)
            held = np.searchsorted(p, starts + size) - np.searchsorted(p, starts)
            if (held >= least).any():
                yield size, starts[held >= least]

    def _needs(self, n: int) -> tuple[list[int], list[int]]:
        """Sizes of windows of a document of n shingles, and how many of a window's shingles some item must have; longer items than the document need more."""
        if n not in self.needs:
            sizes = np.unique(np.minimum(self.sizes, n))
            longer = np.searchsorted(self.lengths, sizes)
            # One entry for each length below the longest item's, and one for all others.
            self.needs[n] = sizes.tolist(), ((4 * (self.lengths[longer] + sizes) + 8) // 9).tolist()
        return self.needs[n]

    def matches(self, bag: np.ndarray, p: np.ndarray) -> list[tuple[int, int, int, float]]:
        """Best window (item, start, size, similarity) of each item that a document holds; p as from places."""
        best: dict[int, tuple[int, int, float]] = {}
        of_item: dict[int, np.ndarray] = {}
        prints = Prints(bag, self.longest, int(p.max(initial=0)) + self.longest)
        sizes = np.minimum(self.sizes, len(bag))
        for size, starts in self.windows(len(bag), p):
            k, found = self.index.near_all(prints.of(starts, size), sizes == size)
            for i in np.unique(found).tolist():
                own = starts[k[found == i]]
                if i not in of_item:
                    of_item[i] = p[np.isin(bag[p], self.bags[i])]
                # A window shares no more with an item than it has places with shingles of it; most windows end here.
                most = np.searchsorted(of_item[i], own + size) - np.searchsorted(of_item[i], own)
                both = size + len(self.bags[i])
                for s, m in zip(own.tolist(), np.minimum(most, len(self.bags[i])).tolist(), strict=True):
                    if 10 * m < 8 * (both - m) or m / (both - m) <= best.get(i, (0, 0, 0.0))[2]:
                        continue
                    shared, total = weighted_jaccard(bag[s : s + size], self.bags[i])
                    if 10 * shared >= 8 * total and shared / total > best.get(i, (0, 0, 0.0))[2]:
                        best[i] = (s, size, shared / total)
        return [(i, *x) for i, x in sorted(best.items())]


def item_groups(benchmark: DataFrame, most: int = ITEM_BYTES) -> Iterator[tuple[list, list]]:
    """Ids and texts of the items, in groups of bounded size."""
    ids, texts, size = [], [], 0
    for r in benchmark.select("item_id", "text").orderBy("item_id", "text").toLocalIterator():
        ids.append(r.item_id)
        texts.append(r.text)
        size += len((r.text or "").encode())
        if size > most:
            yield ids, texts
            ids, texts, size = [], [], 0
    if ids:
        yield ids, texts


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Rows (doc_id, item_id, start_word, n_shingles, similarity): the best window for each item that a document holds."""
    schema = "doc_id bigint, item_id bigint, start_word bigint, n_shingles bigint, similarity double"
    ship_package(docs.sparkSession)
    found = None
    for ids, texts in item_groups(benchmark):
        one = docs.select("doc_id", "text").mapInArrow(_search(ids, texts), schema)
        found = one if found is None else found.unionByName(one)
    return found if found is not None else docs.sparkSession.createDataFrame([], schema)


def _per_text(batch_text: pa.Array, items: Items) -> Iterator[tuple[int, list]]:
    buf, offs = texts_of(batch_text)
    for i, j in slices(offs):
        hashes, at = shingle_rows(LOWER[buf[offs[i] : offs[j]]], offs[i : j + 1] - offs[i])
        p = items.places(hashes)
        cut = np.searchsorted(p, at)
        for r in np.flatnonzero(cut[1:] > cut[:-1]).tolist():
            if m := items.matches(hashes[at[r] : at[r + 1]], p[cut[r] : cut[r + 1]] - at[r]):
                yield i + r, m


def _search(ids: list, texts: list):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items = Items(ids, texts)
        for b in tidy(batches):
            rows = [(r, items.ids[i], s, n, x) for r, m in _per_text(b.column(1), items) for i, s, n, x in m]
            columns = list(zip(*rows, strict=True)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(columns[0], pa.int64())), *(pa.array(c, pa.int64()) for c in columns[1:4]), pa.array(columns[4], pa.float64())], ["doc_id", "item_id", "start_word", "n_shingles", "similarity"])

    return run


def without_benchmark(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs that hold no item, with all their columns."""
    ship_package(docs.sparkSession)
    at = docs.columns.index("text")
    for ids, texts in item_groups(benchmark):

        def run(batches: Iterator[pa.RecordBatch], ids=ids, texts=texts) -> Iterator[pa.RecordBatch]:
            items = Items(ids, texts)
            for b in tidy(batches):
                keep = np.ones(b.num_rows, bool)
                keep[[r for r, _ in _per_text(b.column(at), items)]] = False
                yield b.filter(pa.array(keep))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
