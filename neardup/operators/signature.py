"""Minhash signatures and what they estimate."""

from __future__ import annotations

from collections.abc import Callable, Iterator

try:  # the built-in one costs less than that of OpenSSL for short strings
    from _md5 import md5
except ImportError:
    from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from neardup.config import DedupConfig
from neardup.functions.hashing import LOW, PRIME, XX, finished, gram_number, minhashes, premixed, portable_seeds, seeds
from neardup.functions.text import gram_sets, grams_of, words
from neardup.session import materialize, release_shuffles, ship_package


def gram_numbers(df: DataFrame, cfg: DedupConfig) -> DataFrame:
    """(doc_id, numbers): what a family hashes; documents without grams are left out, as they match nothing."""
    if cfg.family == "portable" and (cfg.shingle, cfg.stem, cfg.short_doc) == ("word", "none", "whole"):
        ship_package(df.sparkSession)
        return df.select("doc_id", F.array_join(words("text"), " ").alias("words")).mapInArrow(_md5_numbers(cfg.n), "doc_id bigint, numbers array<bigint>")
    if cfg.family == "portable":
        return grams_of(df, cfg).where(F.size("grams") > 0).select("doc_id", F.transform("grams", lambda g: gram_number("portable", g)).alias("numbers"))
    return gram_sets(df, cfg).where(F.size("grams") > 0).withColumnRenamed("grams", "numbers")


def _md5_numbers(n: int):
    """(doc_id, numbers) of rows (doc_id, words): the first 60 bits of the md5 of each run of n words, each number once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, made = [], []
            for r, text in enumerate(b.column(1)):
                if text := text.as_py():
                    rows.append(r)
                    made.append(np.unique(_digests(text, n, b"")[:, 0] >> np.uint64(4)).view(np.int64))
            if rows:
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, made)]).astype(np.int32)), pa.array(np.concatenate(made)))
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(rows)), lists], ["doc_id", "numbers"])

    return run


def _below_prime(x: np.ndarray) -> np.ndarray:
    """x % PRIME of numbers from 0 to 2 ** 63 - 1, by shifts, as PRIME is 2 ** 31 - 1."""
    x = (x & PRIME) + (x >> 31)
    x = (x & PRIME) + (x >> 31)
    x -= PRIME
    x += (x >> 63) & PRIME  # again PRIME where that went below 0
    return x


CHUNK = 1 << 15


def _seed_state(key: int) -> np.ndarray:
    """State after the key of a function, as xxhash64(key, x) has it before x."""
    start = np.array([42], np.uint64) + XX[4] + np.uint64(8)
    return finished(start, premixed(np.array([key], np.uint64))) + XX[4] + np.uint64(8)


def _hashers(family: str, m: int, seed: int) -> tuple[Callable, list[Callable]]:
    """What is computed of gram numbers once, and the m functions of that."""
    if family == "portable":
        prepare = lambda x: (x >> 30, x & LOW)
        return prepare, [lambda p, a=a, b=b, c=c: _below_prime(a * p[0] + b * p[1] + c) for a, b, c in portable_seeds(m, seed)]
    prepare = lambda x: premixed(x.view(np.uint64))
    return prepare, [lambda p, s=_seed_state(k): finished(s, p).view(np.int64) for k in seeds(m, seed)]


def _minima(values: np.ndarray, starts: np.ndarray, prepare: Callable, hashers: list[Callable]) -> np.ndarray:
    """Least value of each function in each run of values; runs begin at starts and none is empty."""
    held = prepare(values)
    return np.column_stack([np.minimum.reduceat(h(held), starts) for h in hashers])


def signatures(df: DataFrame, cfg: DedupConfig) -> DataFrame:
    """(doc_id, sig) without a shuffle: vectorised over Arrow batches where numpy has the family's hash, else by lambdas.

    A batch is worked on in chunks that fit a core's cache; a longer document is a chunk of its own.
    """
    numbers = gram_numbers(df, cfg)
    if cfg.family == "mm32":
        return numbers.select("doc_id", minhashes(F.col("numbers"), cfg.family, cfg.m, cfg.seed).alias("sig"))
    family, m, seed = cfg.family, cfg.m, cfg.seed

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        prepare, hashers = _hashers(family, m, seed)
        for b in batches:
            lists = b.column(1)
            values, offsets = lists.flatten().to_numpy(zero_copy_only=False), lists.offsets.to_numpy().astype(np.int64)
            offsets = offsets - offsets[0]
            out, at = [], 0
            while at < b.num_rows:
                to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + CHUNK, side="right")) - 1)
                out.append(_minima(values[offsets[at] : offsets[to]], offsets[at:to] - offsets[at], prepare, hashers))
                at = to
            flat = np.concatenate(out) if out else np.zeros((0, m), np.int64)
            sig = pa.ListArray.from_arrays(pa.array(np.arange(0, flat.size + 1, m, dtype=np.int32)), pa.array(flat.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(0), sig], ["doc_id", "sig"])

    return numbers.mapInArrow(run, "doc_id bigint, sig array<bigint>")


def slots(sig: DataFrame) -> DataFrame:
    """(doc_id, slot, h) rows."""
    return sig.select("doc_id", F.posexplode("sig").alias("slot", "h"))


def estimate(a: Column, b: Column) -> Column:
    """Share of slots in which two signatures agree."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda acc, x: acc + x) / F.size(a)


#: An order's keys are the first 76 bits of an md5: these many name a bucket, and 64 are sent.
BUCKET_BITS = 12
#: So many keys are sorted in a task before they go on.
KEYS_HELD = 2_000_000


def _digests(text: str, n: int, prefix: bytes) -> np.ndarray:
    """Rows of two big-endian halves of the md5 of each run of n words, or of all where there are fewer; the words of text are parted by single spaces."""
    raw = text.encode()
    gaps = np.flatnonzero(np.frombuffer(raw, np.uint8) == 32)
    starts, ends = np.append(0, gaps + 1), np.append(gaps, len(raw))
    if len(starts) > n:
        starts, ends = starts[: len(starts) - n + 1], ends[n - 1 :]
    else:
        starts, ends = starts[:1], ends[-1:]
    made = b"".join([md5(prefix + raw[x:y]).digest() for x, y in zip(starts.tolist(), ends.tolist(), strict=True)])
    return np.frombuffer(made, ">u8").astype(np.uint64).reshape(-1, 2)


def _place(halves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and key within it."""
    hi, lo = halves[:, 0], halves[:, 1]
    return (hi >> np.uint64(64 - BUCKET_BITS)).astype(np.int32), (hi << np.uint64(BUCKET_BITS)) | (lo >> np.uint64(64 - BUCKET_BITS))


def _order_keys(prefix: bytes, n: int):
    """From (doc_id, words): a row (bucket, doc_id, own) with each document's least key, and rows (bucket, keys) with the keys of grams, packed."""

    def packed(held: list[np.ndarray]) -> pa.RecordBatch:
        halves = np.concatenate(held)
        bucket, key = _place(halves[np.argsort(halves[:, 0], kind="stable")])
        first = np.append(True, (key[1:] != key[:-1]) | (bucket[1:] != bucket[:-1]))
        bucket, key = bucket[first], key[first]
        cuts = np.append(np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])), len(bucket))
        keys = pa.array([key[i:j].tobytes() for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)], pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(bucket[cuts[:-1]]), pa.nulls(len(keys), pa.int64()), pa.nulls(len(keys), pa.int64()), keys], names)

    names = ["bucket", "doc_id", "own", "keys"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        count = 0
        for b in batches:
            least, rows = [], []
            for r, text in enumerate(b.column(1)):
                if not (text := text.as_py()):
                    continue
                made = _digests(text, n, prefix)
                least.append(made[np.lexsort((made[:, 1], made[:, 0]))[:1]] if len(made) > 1 else made)
                rows.append(r)
                held.append(made)
                count += len(made)
                if count >= KEYS_HELD:
                    yield packed(held)
                    held, count = [], 0
            if rows:
                bucket, own = _place(np.concatenate(least))
                yield pa.RecordBatch.from_arrays([pa.array(bucket), b.column(0).take(pa.array(rows)), pa.array(own.view(np.int64)), pa.nulls(len(rows), pa.binary())], names)
        if held:
            yield packed(held)

    return run


def _bucket_ranks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows of _order_keys() sorted by bucket: (bucket, doc_id, rank) of each document's key among the distinct keys of its bucket, and (bucket, size)."""
    names = ["bucket", "doc_id", "rank", "size"]

    def done(bucket: int, rows: list[pa.RecordBatch]) -> pa.RecordBatch:
        rows = pa.Table.from_batches(rows)
        packed = rows.column("keys").drop_null()
        keys = np.unique(np.frombuffer(b"".join(k.as_buffer() for k in packed), np.uint64))
        docs = rows.filter(rows.column("own").is_valid())
        ranks = np.searchsorted(keys, docs.column("own").to_numpy().view(np.uint64)) + 1
        ids = pa.concat_arrays([*docs.column("doc_id").chunks, pa.nulls(1, pa.int64())])
        n = len(ranks)
        size = pa.concat_arrays([pa.nulls(n, pa.int64()), pa.array([len(keys)], pa.int64())])
        return pa.RecordBatch.from_arrays([pa.array(np.full(n + 1, bucket, np.int32)), ids, pa.concat_arrays([pa.array(ranks.astype(np.int64)), pa.nulls(1, pa.int64())]), size], names)

    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        bucket = b.column(0).to_numpy()
        cuts = [0, *(np.flatnonzero(bucket[1:] != bucket[:-1]) + 1).tolist(), len(bucket)]
        for i, j in zip(cuts[:-1], cuts[1:], strict=True):
            if i == j:
                continue
            if last is not None and bucket[i] != last:
                yield done(last, held)
                held = []
            held.append(b.slice(i, j - i))
            last = int(bucket[i])
    if held:
        yield done(last, held)


def minhash_permutation(docs: DataFrame, m: int, n: int = 8, seed: int = 42) -> DataFrame:
    """(doc_id, slot, h): the least rank of a document's n-word grams in m orders of all grams, by seeded md5.

    A document's gram of least rank is that of its least md5, so only these are ranked: each is counted in among all distinct grams of its
    bucket, a range of the order. The grams go as packed keys, one order after the other, and each order's files are deleted before the next one.
    Keys are 76 bits long: among 10 ** 9 grams two are alike with a chance of about 1 in 150,000, which would move ranks by one.
    """
    spark, out = docs.sparkSession, None
    ship_package(spark)
    joined = docs.select("doc_id", F.array_join(words("text"), " ").alias("words"))
    for slot in range(m):
        rows = joined.mapInArrow(_order_keys(f"{seed}:{slot}:".encode(), n), "bucket int, doc_id bigint, own bigint, keys binary")
        found = materialize(rows.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_bucket_ranks, "bucket int, doc_id bigint, rank bigint, size bigint"), "order")
        release_shuffles(spark)
        before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)  # one row for each bucket
        sizes = found.where("size IS NOT NULL").select("bucket", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("before"))
        one = found.where("size IS NULL").join(F.broadcast(sizes), "bucket").select("doc_id", F.lit(slot).alias("slot"), (F.col("before") + F.col("rank")).alias("h"))
        out = one if out is None else out.unionByName(one)
    return out.groupBy("doc_id", "slot").agg(F.min("h").alias("h"))
