"""Operation counts, storage and capacity of the methods in closed form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def costs(n: int, w: int, m: int, b: int, p: int, pairs: int = 0, id_bits: int = 32) -> list[tuple[str, float, float, float, float, float, float]]:
    """(method, operations, values in memory, writes, bits of a write, reads, values of a read)."""
    d = -(-n // p)
    return [
        ("all_pairs", float(n) * n * w, float(w), 0.0, 0.0, 0.0, 0.0),
        ("memory", float(n) * w * m + float(n) * m + float(n) * b + pairs, float(n) * b, 0.0, 0.0, 0.0, 0.0),
        ("cells", float(n) * w * m + float(n) * m + float(n) * b + pairs, float(n), float(n) * b, 64.0 + 2 * id_bits, float(b), float(n)),
        ("packed", float(n) * w * m + float(n) * m + float(n) * b + pairs, float(d) * b + n, float(p) * b, 64.0 + 64.0 * d, float(b), float(n)),
        ("forest", float(n) + pairs, float(n), 0.0, 0.0, 0.0, 0.0),
    ]


def cost_table(spark: SparkSession, **given) -> DataFrame:
    return spark.createDataFrame(costs(**given), "method string, operations double, memory_values double, writes double, write_bits double, reads double, read_values double")


def capacity(memory_bytes: float = 4e9, b: int = 50, p: int = 10) -> list[tuple[str, float]]:
    """Documents that fit: b values of 8 bytes each in memory; one value for each with cells; b values for each p-th document when packed."""
    return [("memory", memory_bytes / (8 * b)), ("cells", memory_bytes / 8), ("packed", memory_bytes * p / (8 * b))]


def capacity_table(docs: DataFrame, memory_bytes: float = 4e9, b: int = 50, p: int = 10) -> DataFrame:
    """(layout, documents, tables): how many documents fit, and how many times all those of docs that have words."""
    spark = docs.sparkSession
    rows = spark.createDataFrame(capacity(memory_bytes, b, p), "layout string, documents double")
    held = docs.where(F.col("text").rlike(r"[\p{L}\p{N}]")).agg(F.count("*").alias("n"))
    return rows.crossJoin(F.broadcast(held)).select("layout", "documents", F.round(F.col("documents") / F.greatest(F.lit(1), "n"), 6).alias("tables"))  # one row
