"""Groups of equal documents."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def exact_groups(df: DataFrame, key: str = "text", n: int = 8) -> DataFrame:
    """(doc_id, rep): rep is the lowest id with the same text or the same set of grams; texts without grams stand alone."""
    from neardup.functions.text import word_ngrams, words

    if key == "text":
        keyed = df.where("text IS NOT NULL").select("doc_id", F.sha2("text", 256).alias("k"))
    else:
        grams = df.select("doc_id", word_ngrams(words("text"), n).alias("g"))
        keyed = grams.where(F.size("g") > 0).select("doc_id", F.sha2(F.array_join(F.array_sort("g"), "\n"), 256).alias("k"))
    return keyed.join(keyed.groupBy("k").agg(F.min("doc_id").alias("rep")), "k").select("doc_id", "rep")


def exact_clusters(df: DataFrame, key: str = "text", n: int = 8) -> DataFrame:
    """(rep, size) of the groups of two or more."""
    return exact_groups(df, key, n).groupBy("rep").agg(F.count("*").alias("size")).where("size > 1")


def representatives(df: DataFrame) -> DataFrame:
    """One row (doc_id, text) for each text: what banding needs where copies are many."""
    return df.where("text IS NOT NULL").groupBy(F.sha2("text", 256).alias("k")).agg(F.min_by(F.struct("doc_id", "text"), "doc_id").alias("x")).select("x.doc_id", "x.text")


def expand(pairs: DataFrame, groups: DataFrame) -> DataFrame:
    """Pairs of representatives as pairs of all their copies, and the pairs of copies themselves, with similarity 1."""
    ga, gb = groups.select(F.col("rep").alias("a"), F.col("doc_id").alias("da")), groups.select(F.col("rep").alias("b"), F.col("doc_id").alias("db"))
    across = pairs.join(ga, "a").join(gb, "b").select(F.least("da", "db").alias("a"), F.greatest("da", "db").alias("b"), "jaccard")
    many = groups.join(groups.groupBy("rep").agg(F.count("*").alias("n")).where("n > 1"), "rep")
    inside = many.select("rep", F.col("doc_id").alias("a")).join(many.select("rep", F.col("doc_id").alias("b")), "rep").where("a < b")
    return across.unionByName(inside.select("a", "b", F.lit(1.0).alias("jaccard")))
