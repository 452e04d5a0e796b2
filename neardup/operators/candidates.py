"""Candidate pairs (a, b), a < b, by equal hash or band values."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def _equal_pairs(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Pairs of rows that agree in keys; an equi-join, whose large keys Spark can split."""
    left, right = rows.select(*keys, F.col("doc_id").alias("a")), rows.select(*keys, F.col("doc_id").alias("b"))
    return left.join(right, keys).where("a < b").select("a", "b").distinct()


def inverted_lists(slots: DataFrame, slot_keyed: bool = True) -> DataFrame:
    """Documents that share a value, by lists of the documents of each value; without slot_keyed in any slot."""
    keys = ["slot", "h"] if slot_keyed else ["h"]
    lists = slots.groupBy(*keys).agg(F.collect_set("doc_id").alias("docs")).where(F.size("docs") > 1)
    return lists.select(F.explode("docs").alias("a"), "docs").select("a", F.explode("docs").alias("b")).where("a < b").distinct()


def sorted_runs(slots: DataFrame) -> DataFrame:
    """The same pairs by sorting: each row meets those before it in its run of equal values."""
    order = Window.partitionBy("slot", "h").orderBy("doc_id")
    runs = slots.withColumn("before", F.lag("doc_id").over(order))
    keys = runs.where("before IS NOT NULL").select("slot", "h").distinct()
    return _equal_pairs(slots.join(keys, ["slot", "h"], "left_semi"), ["slot", "h"])


def banded(bands: DataFrame) -> DataFrame:
    """Documents that agree in a band."""
    return _equal_pairs(bands, ["band_id", "value"])


def by_band(bands: DataFrame, ids: list[int]) -> DataFrame:
    """The same pairs with one band after the other: each plan reads one band of the store."""
    found = None
    for k in ids:
        one = _equal_pairs(bands.where(F.col("band_id") == k), ["value"])
        found = one if found is None else found.unionByName(one)
    return found.distinct()


def size_filtered(bands: DataFrame, sizes: DataFrame, threshold: float) -> DataFrame:
    """Banded pairs whose set sizes allow more than the threshold; sizes are (doc_id, n_grams)."""
    rows = bands.join(sizes, "doc_id")
    left = rows.select("band_id", "value", F.col("doc_id").alias("a"), F.col("n_grams").alias("na"))
    right = rows.select("band_id", "value", F.col("doc_id").alias("b"), F.col("n_grams").alias("nb"))
    ok = (F.col("a") < F.col("b")) & (F.least("na", "nb") > threshold * F.greatest("na", "nb"))
    return left.join(right, ["band_id", "value"]).where(ok).select("a", "b").distinct()
