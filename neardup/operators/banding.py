"""Bands of signatures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.config import DedupConfig, bands_for
from neardup.functions.hashing import md5_number


def band_values(sig: DataFrame, r: int, family: str = "xx64", compress: bool = True, b: int | None = None) -> DataFrame:
    """(doc_id, band_id, value): one value for each run of r slots; a 64-bit hash, or the run itself uncompressed."""
    if b is None:
        size = sig.select(F.size("sig").alias("n")).first()
        b = bands_for(size.n, r) if size else 1
    run = lambda i: F.slice("sig", i * r + 1, F.lit(r))
    if not compress:
        value = run
    elif family == "portable":
        value = lambda i: md5_number(F.array_join(F.transform(run(i), lambda x: x.cast("string")), ","))
    else:
        value = lambda i: F.xxhash64(i, run(i))
    return sig.select("doc_id", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(b - 1)), value)).alias("band_id", "value"))


def bands(df: DataFrame, cfg: DedupConfig) -> DataFrame:
    """Band values of documents; signatures are never written nor shuffled."""
    from neardup.operators.signature import signatures

    return band_values(signatures(df, cfg), cfg.r, cfg.family, cfg.compress_bands, cfg.b)
