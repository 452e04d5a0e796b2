"""Operator 2: exact join of documents by the Jaccard similarity of word shingles, with signature trees.

Two documents link when 100 * |A & B| >= 80 * |A | B| for their sets of 5-word shingles.

1. Equal sets form one class; only classes go on, so copies cost one row each.
2. Two linked sets share one of their first n - ceil(0.8 n) + 1 shingles in any common order. The order
   puts shingles last that a sketch of fixed size finds in many documents, so shared passages rarely
   come into these prefixes. Classes that share a prefix shingle form a block; equal blocks are dropped.
3. Each block is searched by a signature tree: nodes hold the OR of their members' token bitmaps and
   their range of sizes, and pairs of nodes are left out when the most that they can share is too little.
   Every pair of a block comes from a traversal of its tree. Members of one component need no further link: small
   blocks give all pairs that the bitmaps allow; larger ones give a spanning set first and, when
   those are verified, all that still leads from one component to another. Blocks of more than CHUNK members are searched in pairs of chunks.
4. The candidates' sets are compared in full, and components are the answer.

Cases: null text has no shingles and links with nothing, as has text without words; fewer than 5 words
count as one shingle; rows with equal doc_id are told apart by the hash of their text and each is in
the component of its own text; rows with a null doc_id have component null and link nothing; an empty table gives no rows; further
columns, whatever their names, are not read, and one_of_each() hands them on.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.common import LOWER, mix, shingle_rows, slices, texts_of, tidy
from neardup.operators.graph import components
from neardup.session import materialize, release, ship_package

#: Cells of the sketch: a task counts up to 255 in each, so its part has 2 MB at any size of the input.
SKETCH_BITS = 21
SKETCH_PARTS = 16
CHUNK = 1_024
#: Blocks of at most so many members give all allowed pairs at once, larger ones a spanning set first.
SMALL = 12
#: A leaf has so many members, or more where a block would have more than about twice LEAVES leaves.
LEAF = 2
LEAVES = 32


def distinct_sets(buf: np.ndarray, offs: np.ndarray, k: int = 5) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    hashes, at = shingle_rows(LOWER[buf], offs, k)
    for lo, hi in pairwise(at.tolist()):
        s = np.sort(hashes[lo:hi])
        yield s[np.concatenate(([True], s[1:] != s[:-1]))] if len(s) > 1 else s


def set_digest(s: np.ndarray) -> tuple[int, int]:
    """Two 64-bit sums that equal sets share."""
    m = mix(s)
    return int(m.sum(dtype=np.uint64).astype(np.int64)), int(mix(m ^ np.uint64(0x5BD1E995)).sum(dtype=np.uint64).astype(np.int64))


def prefix_length(n: int) -> int:
    return n - (4 * n + 4) // 5 + 1


def bitmap(s: np.ndarray) -> bytes:
    """One bit for each shingle, in at least twice as many bits as shingles, a power of two."""
    bits = 1 << max(6, int(2 * len(s) - 1).bit_length())
    flags = np.zeros(bits, bool)
    flags[(s & np.uint64(bits - 1)).astype(np.int64)] = True
    return np.packbits(flags, bitorder="little").tobytes()


def _folded(x: np.ndarray, size: int) -> np.ndarray:
    """A bitmap of fewer bytes: the OR of its equal parts."""
    return np.bitwise_or.reduce(x.reshape(-1, size), 0) if len(x) > size else x


def fold(raw: bytes, size: int) -> np.ndarray:
    return _folded(np.frombuffer(raw, np.uint8), size)


def needed(n, m):
    """The least number of shared shingles with which sets of n and m link."""
    return (4 * (n + m) + 8) // 9


# --- search inside a block -------------------------------------------------------------------------


class Block:
    """Members of a block: id, component, size and bitmap, in order of size."""

    def __init__(self, ids: list[int], comps: list[int], sizes: list[int], maps: list[bytes], sides: list[int] | None = None, lists: list[list[int]] | None = None):
        order = np.lexsort((ids, sizes))
        self.ids, self.comps, self.n = (np.array(x, np.int64)[order] for x in (ids, comps, sizes))
        self.sides = np.array(sides, np.int64)[order] if sides is not None else None
        self.lists = [set(lists[i]) for i in order.tolist()] if lists is not None else None
        self.maps = [maps[i] for i in order.tolist()]
        self.folded: dict[int, np.ndarray] = {}
        self.widths = np.array([len(m) for m in self.maps])

    def at(self, width: int) -> np.ndarray:
        """All bitmaps of at least this width, folded to it; the others are empty."""
        if width not in self.folded:
            out = np.zeros((len(self.maps), width), np.uint8)
            for i in np.flatnonzero(self.widths >= width).tolist():
                out[i] = fold(self.maps[i], width)
            self.folded[width] = out
        return self.folded[width]

    def allowed(self, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pairs that sizes and bitmaps allow, with the room above what they need."""
        ok = (4 * np.maximum(self.n[i], self.n[j]) <= 5 * np.minimum(self.n[i], self.n[j])) & (self.comps[i] != self.comps[j])
        i, j = i[ok], j[ok]
        room = np.empty(len(i), np.int64)
        width = np.minimum(self.widths[i], self.widths[j])
        for w in np.unique(width).tolist():
            k = np.flatnonzero(width == w)
            maps = self.at(w)
            a, b = maps[i[k]], maps[j[k]]
            only_a = np.bitwise_count(a & ~b).sum(1, dtype=np.int64)
            only_b = np.bitwise_count(b & ~a).sum(1, dtype=np.int64)
            room[k] = np.minimum(self.n[i[k]] - only_a, self.n[j[k]] - only_b) - needed(self.n[i[k]], self.n[j[k]])
        ok = room >= 0
        return i[ok], j[ok], room[ok]

    def own(self, bid: int, across: bool) -> tuple[np.ndarray, np.ndarray]:
        """Allowed pairs that belong to this block: it is the lowest that both are in, and, if across, they are of two sides."""
        out_i, out_j = [], []
        for i, j in SignatureTree(self).leaf_pairs():
            if across:
                ok = self.sides[i] != self.sides[j]
                i, j = i[ok], j[ok]
            i, j, _ = self.allowed(i, j)
            for x, y in zip(i.tolist(), j.tolist(), strict=True):
                if min(self.lists[x] & self.lists[y]) == bid:
                    out_i.append(x)
                    out_j.append(y)
        return self.ids[np.array(out_i, np.int64)], self.ids[np.array(out_j, np.int64)]

    def all_pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """All allowed pairs, found by dual traversal of the signature tree with itself."""
        out_i, out_j = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for i, j in SignatureTree(self).leaf_pairs():
            i, j, _ = self.allowed(i, j)
            out_i.append(self.ids[i])
            out_j.append(self.ids[j])
        return np.concatenate(out_i), np.concatenate(out_j)

    def spanning_pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """Allowed pairs found by dual traversal of the signature tree with itself, but for those that earlier ones already join."""
        tree = SignatureTree(self)
        root = {int(c): int(c) for c in np.unique(self.comps)}

        def find(c: int) -> int:
            while root[c] != c:
                root[c] = root[root[c]]
                c = root[c]
            return c

        out_i, out_j = [], []
        for i, j in tree.leaf_pairs():
            i, j, room = self.allowed(i, j)
            for k in np.argsort(-room, kind="stable").tolist():
                a, b = find(int(self.comps[i[k]])), find(int(self.comps[j[k]]))
                if a != b:
                    root[max(a, b)] = min(a, b)
                    out_i.append(int(i[k]))
                    out_j.append(int(j[k]))
        return self.ids[np.array(out_i, np.int64)], self.ids[np.array(out_j, np.int64)]


class SignatureTree:
    """Binary tree over the members of a block in order of size; looked and pruned count the pairs of nodes that a traversal meets and leaves out."""

    def __init__(self, block: Block):
        self.block, self.nodes = block, []
        self.leaf = max(LEAF, len(block.ids) // LEAVES)
        self.looked = self.pruned = 0
        self.root = self._build(0, len(block.ids))

    def _build(self, lo: int, hi: int) -> int:
        b = self.block
        if hi - lo == len(b.ids) <= self.leaf:
            # The whole block is one leaf: there is no pair of nodes to leave out.
            width, ors, fewest, kids = 0, np.zeros(0, np.uint8), 0, None
        elif hi - lo <= self.leaf:
            width = int(b.widths[lo:hi].min())
            maps = b.at(width)[lo:hi]
            ors, fewest, kids = np.bitwise_or.reduce(maps, 0), int(np.bitwise_count(maps).sum(1, dtype=np.int64).min()), None
        else:
            mid = (lo + hi) // 2
            kids = (self._build(lo, mid), self._build(mid, hi))
            x, y = (self.nodes[k] for k in kids)
            width = min(len(x["or"]), len(y["or"]))
            ors = _folded(x["or"], width) | _folded(y["or"], width)
            fewest = int(min(np.bitwise_count(b.at(width)[lo:hi]).sum(1, dtype=np.int64))) if width < max(len(x["or"]), len(y["or"])) else min(x["fewest"], y["fewest"])
        comps = b.comps[lo:hi]
        self.nodes.append({"lo": lo, "hi": hi, "or": ors, "fewest": fewest, "least": int(b.n[lo]), "most": int(b.n[hi - 1]), "kids": kids, "one": int(comps[0]) if (comps == comps[0]).all() else None})
        return len(self.nodes) - 1

    def _possible(self, x: dict, y: dict) -> bool:
        """False if no pair of members can share enough, or all members are in one component."""
        if x["one"] is not None and x["one"] == y["one"]:
            return False
        if x is y and x["kids"] is None:
            return True
        if 4 * max(x["least"], y["least"]) > 5 * min(x["most"], y["most"]):
            return False
        width = min(len(x["or"]), len(y["or"]))
        both = int(np.bitwise_count(_folded(x["or"], width) & _folded(y["or"], width)).sum())
        most = min((n["most"] - max(0, n["fewest"] - both)) if len(n["or"]) == width else n["most"] for n in (x, y))
        return most >= needed(x["least"], y["least"])

    def leaf_pairs(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        todo = [(self.root, self.root)]
        while todo:
            p, q = todo.pop()
            x, y = self.nodes[p], self.nodes[q]
            self.looked += 1
            if not self._possible(x, y):
                self.pruned += 1
                continue
            if x["kids"] is None and y["kids"] is None:
                if p == q:
                    i, j = np.triu_indices(x["hi"] - x["lo"], 1)
                    yield i + x["lo"], j + x["lo"]
                else:
                    i, j = np.meshgrid(np.arange(x["lo"], x["hi"]), np.arange(y["lo"], y["hi"]), indexing="ij")
                    yield i.ravel(), j.ravel()
            elif p == q:
                a, b = x["kids"]
                todo += [(a, b), (b, b), (a, a)]
            elif x["kids"] is not None and (y["kids"] is None or x["hi"] - x["lo"] >= y["hi"] - y["lo"]):
                todo += [(k, q) for k in x["kids"]]
            else:
                todo += [(p, k) for k in y["kids"]]


# --- the join ---------------------------------------------------------------------------------------


def _texts(docs: DataFrame) -> DataFrame:
    ship_package(docs.sparkSession)
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select("doc_id", F.xxhash64(text).alias("t"), text.alias("text"))


def _survey(texts: DataFrame) -> DataFrame:
    """Rows of documents (doc_id, t, n, s1, s2), and of sketch parts (part, counts) from each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "t", "n", "s1", "s2", "part", "counts"]
        counts = np.zeros(1 << SKETCH_BITS, np.uint32)
        for b in tidy(batches):
            buf, offs = texts_of(b.column(2))
            for i, j in slices(offs):
                n, s1, s2 = [], [], []
                for s in distinct_sets(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i]):
                    np.add.at(counts, (s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), 1)
                    x, y = set_digest(s) if len(s) else (0, 0)
                    n.append(len(s))
                    s1.append(x)
                    s2.append(y)
                none = pa.nulls(j - i, pa.int32()), pa.nulls(j - i, pa.binary())
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), b.column(1).slice(i, j - i), *(pa.array(x, pa.int64()) for x in (n, s1, s2)), *none], names)
        parts = [np.minimum(p, 255).astype(np.uint8).tobytes() for p in np.split(counts, SKETCH_PARTS)]
        none = [pa.nulls(SKETCH_PARTS, pa.int64()) for _ in range(5)]
        yield pa.RecordBatch.from_arrays([*none, pa.array(range(SKETCH_PARTS), pa.int32()), pa.array(parts, pa.binary())], names)

    return texts.mapInArrow(run, "doc_id bigint, t bigint, n bigint, s1 bigint, s2 bigint, part int, counts binary")


def _levels(survey: DataFrame) -> np.ndarray:
    """For each cell of the sketch how full it is, in steps; 2 ** SKETCH_BITS bytes at any size."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for b in tidy(batches):
            for p, c in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                own = np.frombuffer(c, np.uint8).astype(np.uint32)
                total[p] = total[p] + own if p in total else own
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([v.tobytes() for v in total.values()], pa.binary())], ["part", "counts"])

    rows = survey.where("part IS NOT NULL").select("part", "counts").repartition(SKETCH_PARTS, "part").mapInArrow(add, "part int, counts binary").collect()
    # Part by part: the driver holds 8 MB of counts and 2 MB of levels at any size of the input.
    parts = {r.part: np.frombuffer(r.counts, np.uint32) for r in rows}
    mean = max(1.0, sum(int(c.sum(dtype=np.int64)) for c in parts.values()) / (1 << SKETCH_BITS))
    size = (1 << SKETCH_BITS) // SKETCH_PARTS
    out = np.zeros(1 << SKETCH_BITS, np.uint8)
    for p, c in parts.items():
        z = (c.astype(np.float32) - np.float32(mean)) / np.float32(mean**0.5)
        # Quarters of a deviation around the mean, eighths of a doubling far above it.
        near = np.clip(np.floor(4 * (z + 4)), 0, 48)
        out[p * size : (p + 1) * size] = np.minimum(255, np.where(z < 8, near, 48 + np.ceil(8 * np.log2(np.maximum(z, 8) / 8))))
    return out


def _signatures(texts: DataFrame, levels: np.ndarray) -> DataFrame:
    """Rows (n, s1, s2, prefix, bits) of documents with shingles."""
    raw = levels.tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level = np.frombuffer(raw, np.uint8)
        for b in tidy(batches):
            buf, offs = texts_of(b.column(0))
            for i, j in slices(offs):
                n, s1, s2, prefix, bits = [], [], [], [], []
                for s in distinct_sets(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i]):
                    if not len(s):
                        continue
                    x, y = set_digest(s)
                    k = prefix_length(len(s))
                    order = np.argsort(level[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)], kind="stable")[:k]
                    n.append(len(s))
                    s1.append(x)
                    s2.append(y)
                    prefix.append(s[order].view(np.int64))
                    bits.append(bitmap(s))
                yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in (n, s1, s2)), pa.array(prefix, pa.list_(pa.int64())), pa.array(bits, pa.binary())], ["n", "s1", "s2", "prefix", "bits"])

    return texts.select("text").mapInArrow(run, "n bigint, s1 bigint, s2 bigint, prefix array<bigint>, bits binary")


def _blocks(tokens: DataFrame) -> DataFrame:
    """Rows (bid, chunk, members) from (token, cid): the classes that share a token, equal sets of classes once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        rows: list[tuple[int, int, list[int]]] = []
        token, run_ids, chunk = None, np.zeros(0, np.int64), 0

        def close() -> None:
            nonlocal run_ids, chunk
            if chunk:
                if len(run_ids):
                    rows.append((int(token), chunk, run_ids.tolist()))
            elif len(run_ids) > 1:
                key = (int(mix(run_ids.view(np.uint64)).sum(dtype=np.uint64).astype(np.int64)), len(run_ids))
                if key not in seen:
                    if len(seen) > 1_000_000:
                        seen.clear()
                    seen.add(key)
                    rows.append((key[0], 0, run_ids.tolist()))
            run_ids, chunk = np.zeros(0, np.int64), 0

        def batch() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.list_(pa.int64()))], ["bid", "chunk", "members"])
            rows.clear()
            return out

        for b in tidy(batches):
            t, c = b.column(0).to_numpy(), b.column(1).to_numpy()
            cuts = np.concatenate(([0], np.flatnonzero(t[1:] != t[:-1]) + 1, [len(t)]))
            sizes = np.diff(cuts)
            # Only runs of two or more matter, beside the first and last, which may go on in other batches.
            for k in sorted({0, len(sizes) - 1} | set(np.flatnonzero(sizes > 1).tolist())) if len(t) else ():
                lo, hi = int(cuts[k]), int(cuts[k + 1])
                if t[lo] != token:
                    close()
                    token = t[lo]
                run_ids = np.concatenate((run_ids, c[lo:hi])) if len(run_ids) else c[lo:hi]
                while len(run_ids) > CHUNK:
                    rows.append((int(token), chunk, run_ids[:CHUNK].tolist()))
                    run_ids, chunk = run_ids[CHUNK:], chunk + 1
            if len(rows) > 256:
                yield batch()
        close()
        if rows:
            yield batch()

    dealt = tokens.repartition("token").sortWithinPartitions("token", "cid")
    return dealt.mapInArrow(run, "bid bigint, chunk int, members array<bigint>").dropDuplicates(["bid", "chunk"])


def _first_tasks(blocks: DataFrame) -> DataFrame:
    """Rows (bid, p, q, cid): the members of a block, or of its first chunk and another one."""
    top = blocks.groupBy("bid").agg(F.max("chunk").alias("top"))
    parts = blocks.join(top, "bid")
    single = parts.where("top = 0").select("bid", F.lit(0).alias("p"), F.lit(0).alias("q"), F.explode("members").alias("cid"))
    many = parts.where("top > 0")
    other = many.where("chunk > 0").select("bid", F.lit(0).alias("p"), F.col("chunk").alias("q"), F.explode("members").alias("cid"))
    first = many.where("chunk = 0").select("bid", F.lit(0).alias("p"), F.explode(F.sequence(F.lit(1), "top")).alias("q"), "members")
    return single.unionByName(other).unionByName(first.select("bid", "p", "q", F.explode("members").alias("cid")))


def _last_tasks(blocks: DataFrame, comps: DataFrame) -> DataFrame:
    """Rows (bid, p, q, side, cid, comp, bids): each chunk with itself and with each other one, where more than one component is left.

    bids lists the large open blocks of a class, so that a pair is looked at in the lowest common one alone.
    """
    large = blocks.join(blocks.where((F.size("members") > SMALL) | (F.col("chunk") > 0)).select("bid").distinct(), "bid", "left_semi")
    flat = large.select("bid", "chunk", F.explode("members").alias("cid")).join(comps, "cid")
    open_ = flat.groupBy("bid").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("bid")
    flat = materialize(flat.join(open_, "bid", "left_semi"), "open-blocks")
    lists = flat.groupBy("cid").agg(F.collect_set("bid").alias("bids"))
    ends = flat.groupBy("bid", "chunk").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"))
    x, y = ends.select("bid", F.col("chunk").alias("p"), F.col("lo").alias("lo1"), F.col("hi").alias("hi1")), ends.select("bid", F.col("chunk").alias("q"), F.col("lo").alias("lo2"), F.col("hi").alias("hi2"))
    pairs = materialize(x.join(y, "bid").where("p <= q AND least(lo1, lo2) < greatest(hi1, hi2)").select("bid", "p", "q"), "chunk-pairs")
    rows = flat.join(lists, "cid")
    left = rows.withColumnRenamed("chunk", "p").join(pairs, ["bid", "p"]).select("bid", "p", "q", F.lit(0).alias("side"), "cid", "comp", "bids")
    right = rows.withColumnRenamed("chunk", "q").join(pairs.where("p < q"), ["bid", "q"]).select("bid", "p", "q", F.lit(1).alias("side"), "cid", "comp", "bids")
    return left.unionByName(right)


def _search(tasks: DataFrame, classes: DataFrame, last: bool) -> DataFrame:
    """Candidate pairs (a, b) of classes: a spanning set of each block's, or the last time all pairs across components."""
    known = classes.select("cid", "n", "bits")
    flat = tasks.join(known, "cid")
    if not last:
        flat = flat.select("*", F.col("cid").alias("comp"), F.lit(0).alias("side"), F.array().cast("array<bigint>").alias("bids"))
    whole = flat.groupBy("bid", "p", "q").agg(F.collect_list(F.struct("cid", "comp", "n", "bits", "side", "bids")).alias("m"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tidy(batches):
            out_a, out_b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for k in range(b.num_rows):
                m = b.column(3)[k].values
                fields = [m.field(i).to_pylist() for i in range(6 if last else 4)]
                block = Block(*fields)
                if last:
                    i, j = block.own(b.column(0)[k].as_py(), b.column(1)[k].as_py() != b.column(2)[k].as_py())
                else:
                    i, j = block.all_pairs() if len(block.ids) <= SMALL else block.spanning_pairs()
                out_a.append(np.minimum(i, j))
                out_b.append(np.maximum(i, j))
            pair = np.unique(np.column_stack((np.concatenate(out_a), np.concatenate(out_b))), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"])

    return whole.select("bid", "p", "q", "m").mapInArrow(run, "a bigint, b bigint").distinct()


def _sets(ids: DataFrame, classes: DataFrame, texts: DataFrame) -> DataFrame:
    """Rows (cid, s) with the full sets of some classes."""
    wanted = ids.join(classes.select("cid", "one"), "cid").select("cid", F.col("one.doc_id").alias("doc_id"), F.col("one.t").alias("t"))
    found = texts.join(wanted, ["doc_id", "t"]).select("cid", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in tidy(batches):
            buf, offs = texts_of(b.column(1))
            for i, j in slices(offs):
                sets = [s.view(np.int64) for s in distinct_sets(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i])]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array(sets, pa.list_(pa.int64()))], ["cid", "s"])

    return found.mapInArrow(run, "cid bigint, s array<bigint>")


def _sets_for(pairs: DataFrame, known: DataFrame | None, classes: DataFrame, texts: DataFrame) -> DataFrame:
    """The full sets of the pairs' classes; only those that aren't known are made from texts."""
    ids = pairs.select(F.col("a").alias("cid")).unionByName(pairs.select(F.col("b").alias("cid"))).distinct()
    if known is None:
        return materialize(_sets(ids, classes, texts), "sets")
    missing = materialize(ids.join(known.select("cid"), "cid", "left_anti"), "missing")
    return known if missing.isEmpty() else known.unionByName(materialize(_sets(missing, classes, texts), "sets"))


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) that link."""
    a, b = sets.select(F.col("cid").alias("a"), F.col("s").alias("x")), sets.select(F.col("cid").alias("b"), F.col("s").alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for p in tidy(batches):
            keep = np.zeros(p.num_rows, bool)
            for k in range(p.num_rows):
                x, y = p.column(2)[k].values.to_numpy(), p.column(3)[k].values.to_numpy()
                shared = len(np.intersect1d(x, y, assume_unique=True))
                keep[k] = 100 * shared >= 80 * (len(x) + len(y) - shared)
            yield p.select(["a", "b"]).filter(pa.array(keep))

    return pairs.join(a, "a").join(b, "b").select("a", "b", "x", "y").mapInArrow(run, "a bigint, b bigint")


def _found(docs: DataFrame) -> DataFrame:
    """One row (doc_id, t, n_shingles, component_id, one) for each document; one is the lowest (doc_id, t) of its component."""
    texts = _texts(docs)
    survey = materialize(_survey(texts), "survey")
    own = survey.where("part IS NULL")
    levels = _levels(survey)
    sets_of = own.where("n > 0 AND doc_id IS NOT NULL").groupBy("n", "s1", "s2").agg(F.min(F.struct("doc_id", "t")).alias("one"))
    unique = _signatures(texts.where("doc_id IS NOT NULL"), levels).groupBy("n", "s1", "s2").agg(F.first("prefix").alias("prefix"), F.first("bits").alias("bits"))
    classes = materialize(unique.join(sets_of, ["n", "s1", "s2"]).withColumn("cid", F.monotonically_increasing_id()), "classes")
    tokens = classes.select(F.explode("prefix").alias("token"), "cid")
    blocks = materialize(_blocks(tokens), "blocks")
    pairs = materialize(_search(_first_tasks(blocks), classes, False), "pairs")
    sets = _sets_for(pairs, None, classes, texts)
    links = materialize(_verified(pairs, sets), "links")
    comps = _with_components(classes, links)
    more = materialize(_search(_last_tasks(blocks, comps), classes, True).join(pairs, ["a", "b"], "left_anti"), "pairs")
    if not more.isEmpty():
        links = materialize(links.unionByName(_verified(more, _sets_for(more, sets, classes, texts))), "links")
        comps = _with_components(classes, links)
    release(blocks, pairs, more, sets, links)
    lowest = comps.join(classes.select("cid", F.col("one").alias("low"), "n", "s1", "s2"), "cid")
    lowest = lowest.join(lowest.groupBy("comp").agg(F.min("low").alias("one")), "comp").select("n", "s1", "s2", "one")
    rows = own.select("doc_id", "t", F.col("n").alias("n_shingles"), "n", "s1", "s2").join(lowest, ["n", "s1", "s2"], "left")
    return rows.select("doc_id", "t", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("one.doc_id", "doc_id")).alias("component_id"), F.when(F.col("doc_id").isNotNull(), F.col("one")).alias("one"))


def shingle_components(docs: DataFrame) -> DataFrame:
    """One row (doc_id, n_shingles, component_id) for each document."""
    return _found(docs).select("doc_id", "n_shingles", "component_id")


def _with_components(classes: DataFrame, links: DataFrame) -> DataFrame:
    """(cid, comp) for all classes."""
    found = components(links)
    return materialize(classes.select("cid").join(found.withColumnRenamed("id", "cid"), "cid", "left").select("cid", F.coalesce("component", "cid").alias("comp")), "components")


def one_of_each(docs: DataFrame) -> DataFrame:
    """The rows of docs that stand for their component: the one with the lowest doc_id and, among these, hash of its text; all columns stay.

    Of rows alike in doc_id and text one stays. Rows that have no shingles, or no doc_id, link with nothing and stay.
    """
    found = _found(docs.select("doc_id", "text")).where("one IS NOT NULL").groupBy("doc_id", "t", "one").agg(F.count("*").alias("rows"))
    fate = materialize(found.select(F.col("doc_id").alias("d"), F.col("t").alias("h"), F.struct("doc_id", "t").eqNullSafe(F.col("one")).alias("first"), "rows").where("NOT first OR rows > 1"), "fate")
    # All columns travel in one struct, so that no name of theirs can clash.
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.col("doc_id").alias("d"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("h"))
    # What goes grows with the documents: no broadcast.
    kept = keyed.join(fate.hint("merge"), ["d", "h"], "left_anti")
    again = fate.where("first")
    if not again.isEmpty():
        kept = kept.unionByName(keyed.join(again.hint("merge"), ["d", "h"], "left_semi").dropDuplicates(["d", "h"]))
    return kept.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))
