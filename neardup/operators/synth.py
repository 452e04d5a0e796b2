"""Perturbed copies of documents, by md5 alone, so that any engine makes the same text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from neardup.functions.hashing import md5_number
from neardup.operators.ranks import ranked
from neardup.session import materialize


def _draw(*parts: Column) -> Column:
    """A number in 0..1 from the md5 of parts."""
    return md5_number(F.concat_ws("|", *[p.cast("string") for p in parts])) / float(1 << 60)


def inject(df: DataFrame, copies: int, lo: float, hi: float, seed: int = 42, pool: int | None = None) -> DataFrame:
    """df (doc_id, text) with copies added: (doc_id, text, origin_id, rate).

    Copy k takes a source by rank of its id (the first pool ones alone, if given), a rate from lo to hi, and
    replaces each word with that chance by a made-up one; ids follow the highest one.
    """
    base = df.select("doc_id", "text")
    spark = df.sparkSession
    stats = base.agg(F.max("doc_id").alias("top"), F.count("*").alias("n")).first()
    n = min(stats.n, pool or stats.n)
    s = F.lit(seed)
    wanted = spark.range(copies).select("id", F.floor(_draw(s, F.lit("source"), F.col("id")) * n).alias("rank"), (F.lit(lo) + (hi - lo) * _draw(s, F.lit("rate"), F.col("id"))).alias("rate"))
    # Ids alone are ranked and few are drawn: no text but the drawn ones moves.
    sources = ranked(base.select("doc_id") if n == stats.n else base.select("doc_id").orderBy("doc_id").limit(n), "doc_id")
    drawn = wanted.join(sources, "rank").dropDuplicates(["id"])
    picked = base.join(F.broadcast(drawn), "doc_id").dropDuplicates(["id"])
    words = F.split("text", " ")
    changed = F.transform(words, lambda w, i: F.when(_draw(s, F.col("id"), i) < F.col("rate"), F.concat(F.lit("x"), F.substring(F.md5(F.concat_ws("|", F.lit("w"), F.col("id").cast("string"), i.cast("string"))), 1, 6))).otherwise(w))
    made = materialize(picked.select((F.lit(stats.top + 1) + F.col("id")).alias("doc_id"), F.array_join(changed, " ").alias("text"), F.col("doc_id").alias("origin_id"), "rate"), "copies")
    return base.select("doc_id", "text", F.col("doc_id").alias("origin_id"), F.lit(0.0).alias("rate")).unionByName(made)
