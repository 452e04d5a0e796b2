"""Hash families for minhash, their seeds, and the numbering of grams."""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

PRIME = (1 << 31) - 1
LOW = (1 << 30) - 1


def seeds(m: int, seed: int = 42) -> list[int]:
    r = random.Random(seed)
    return [r.getrandbits(62) for _ in range(m)]


def portable_seeds(m: int, seed: int = 42) -> list[tuple[int, int, int]]:
    r = random.Random(seed)
    return [(r.randrange(1, PRIME), r.randrange(1, PRIME), r.randrange(PRIME)) for _ in range(m)]


def md5_number(c: Column) -> Column:
    """The first 60 bits of a string's md5."""
    return F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("bigint")


def gram_number(family: str, gram: Column) -> Column:
    """The number of a gram that the family hashes."""
    return md5_number(gram) if family == "portable" else F.xxhash64(gram)


def minhashes(numbers: Column, family: str, m: int, seed: int = 42) -> Column:
    """Array of m minima over an array of gram numbers, which is computed once for each row."""
    if family == "portable":
        keys = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(c).alias("c")) for a, b, c in portable_seeds(m, seed)])
        one = lambda k, x: (k.a * F.shiftright(x, 30) + k.b * x.bitwiseAND(F.lit(LOW)) + k.c) % PRIME
    else:
        keys = F.array(*[F.lit(k) for k in seeds(m, seed)])
        mixed = F.xxhash64 if family == "xx64" else (lambda *c: F.hash(*c).cast("bigint"))
        one = lambda k, x: mixed(k, x)
    return F.element_at(F.transform(F.array(numbers), lambda xs: F.transform(keys, lambda k: F.array_min(F.transform(xs, lambda x: one(k, x))))), 1)


def expected_collisions(grams: float, bits: int) -> float:
    """Expected pairs of grams with one number among 2 ** bits."""
    return grams * (grams - 1) / 2 ** (bits + 1)


def gram_dictionary(exploded: DataFrame, buckets: int = 64) -> DataFrame:
    """(gram, gram_id): grams numbered from 0 in their order, within buckets of a hash, without one task for all."""
    distinct = exploded.select("gram").distinct().withColumn("bucket", F.pmod(F.xxhash64("gram"), F.lit(buckets)).cast("int"))
    sizes = distinct.groupBy("bucket").agg(F.count("*").alias("n"))
    starts = sizes.select("bucket", F.coalesce(F.sum("n").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    place = F.row_number().over(Window.partitionBy("bucket").orderBy("gram")) - 1
    return distinct.withColumn("place", place).join(F.broadcast(starts), "bucket").select("gram", (F.col("start") + F.col("place")).alias("gram_id"))


#: The primes of the published 64-bit hash that the built-in xxhash64 function computes.
XX = tuple(map(np.uint64, (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)))


def _rotated(x: np.ndarray, k: int) -> np.ndarray:
    return (x << np.uint64(k)) | (x >> np.uint64(64 - k))


def premixed(x: np.ndarray) -> np.ndarray:
    return _rotated(x * XX[1], 31) * XX[0]


def finished(state: np.ndarray, mixed: np.ndarray) -> np.ndarray:
    h = _rotated(state ^ mixed, 27)
    h *= XX[0]
    h += XX[3]
    h ^= h >> np.uint64(33)
    h *= XX[1]
    h ^= h >> np.uint64(29)
    h *= XX[2]
    h ^= h >> np.uint64(32)
    return h
