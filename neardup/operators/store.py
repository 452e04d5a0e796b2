"""Stores of band values: one row for each cell, or arrays of slices of documents. Both lie in folders by band."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.operators.ranks import ranked as by_rank


def write_cells(bands: DataFrame, path: str) -> None:
    """(band_id, doc_id, value) rows; tasks hold whole bands, so each band is few files."""
    bands.repartition("band_id", F.pmod(F.xxhash64("doc_id"), F.lit(8))).write.partitionBy("band_id").parquet(path)


def read_cells(spark: SparkSession, path: str, band_id: int | None = None) -> DataFrame:
    """All cells, or those of one band: its folder alone is read."""
    rows = spark.read.parquet(path).select("band_id", "doc_id", "value")
    return rows if band_id is None else rows.where(F.col("band_id") == band_id)


def slice_ids(docs: DataFrame, slices: int, ranked: bool = False) -> DataFrame:
    """(doc_id, slice_id): by hash, or by rank with slices of equal size, the first ones a document longer where it doesn't come out even."""
    if ranked:
        n = docs.count()
        size, longer = n // slices, n % slices
        rank, edge = F.col("rank"), longer * (size + 1)
        slice_id = F.when(rank < edge, F.floor(rank / (size + 1))).otherwise(longer + F.floor((rank - edge) / max(1, size)))
        return by_rank(docs.select("doc_id"), "doc_id").select("doc_id", slice_id.cast("int").alias("slice_id"))
    return docs.select("doc_id", F.pmod(F.xxhash64("doc_id"), F.lit(slices)).cast("int").alias("slice_id"))


def slice_size(n_docs: int, per_slice: int) -> int:
    """Slices needed so that each has so many documents, the last fewer."""
    return max(1, -(-n_docs // per_slice))


def pack(bands: DataFrame, slices: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows (slice_id, band_id, value array) in order of doc_id, and the directory (slice_id, doc_ids)."""
    rows = bands.join(slices, "doc_id")
    packed = rows.groupBy("slice_id", "band_id").agg(F.array_sort(F.collect_list(F.struct("doc_id", "value"))).alias("x")).select("slice_id", "band_id", F.col("x.value").alias("value"))
    directory = rows.select("slice_id", "doc_id").distinct().groupBy("slice_id").agg(F.array_sort(F.collect_list("doc_id")).alias("doc_ids"))
    return packed, directory


def write_packed(bands: DataFrame, slices: DataFrame, path: str) -> None:
    packed, directory = pack(bands, slices)
    packed.write.partitionBy("band_id").parquet(f"{path}/bands")
    directory.write.parquet(f"{path}/directory")


def unpack(packed: DataFrame, directory: DataFrame) -> DataFrame:
    """(band_id, doc_id, value) rows of a packed store; the order of a slice is that of its directory entry."""
    both = packed.join(directory, "slice_id").select("band_id", F.arrays_zip(F.col("doc_ids").alias("doc_id"), F.col("value").alias("value")).alias("x"))
    return both.select("band_id", F.explode("x").alias("x")).select("band_id", "x.doc_id", "x.value")


def read_packed(spark: SparkSession, path: str, band_id: int | None = None) -> DataFrame:
    packed = spark.read.parquet(f"{path}/bands").select("slice_id", "band_id", "value")
    return unpack(packed if band_id is None else packed.where(F.col("band_id") == band_id), spark.read.parquet(f"{path}/directory"))
