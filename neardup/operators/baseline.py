"""Timing and memory of the layouts, as measured where it runs."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.config import DedupConfig
from neardup.functions.text import grams_of
from neardup.io import spread_documents as documents
from neardup.operators import candidates, store, verify
from neardup.operators.banding import bands
from neardup.operators.forest import fold_buckets
from neardup.operators.graph import components
from neardup.plans.pipeline import stored_bands
from neardup.session import materialize, scratch_path


def timed(work) -> float:
    began = time.perf_counter()
    work()
    return time.perf_counter() - began


def run_out(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def stage_times(spark: SparkSession, d: str) -> DataFrame:
    """(stage, seconds) of one run: bands to a store, candidates, exact check."""
    docs, cfg, path = documents(spark, d), DedupConfig(), scratch_path(spark, "cells")
    rows = [("write", timed(lambda: store.write_cells(bands(docs, cfg), path)))]
    cells = store.read_cells(spark, path)
    held: dict[str, DataFrame] = {}
    rows.append(("candidates", timed(lambda: held.update(c=materialize(candidates.banded(cells), "candidates")))))
    rows.append(("verify", timed(lambda: run_out(verify.verified(held["c"], grams_of(docs, cfg, hashed=True), 0.75)))))
    return spark.createDataFrame(rows, "stage string, seconds double")


def scaling_times(spark: SparkSession, d: str) -> DataFrame:
    """(layout, b, seconds) from text to candidates: growth with bands for each layout."""
    docs, rows = documents(spark, d), []
    for layout in ("memory", "cells", "packed"):
        for b in (10, 20, 50) if layout == "memory" else (50,):
            cfg = DedupConfig(layout=layout, b=b)
            rows.append((layout, b, timed(lambda cfg=cfg: run_out(candidates.banded(stored_bands(docs, cfg))))))
    return spark.createDataFrame(rows, "layout string, b int, seconds double")


def multiplied(docs: DataFrame, times: int) -> DataFrame:
    """times as many documents: each further set has all texts with other words of the same number, and its own ids."""
    if times == 1:
        return docs.select("doc_id", "text")
    top = docs.agg(F.max("doc_id").alias("top")).first().top or 0
    sets = docs.select("doc_id", "text").crossJoin(F.broadcast(docs.sparkSession.range(times).withColumnRenamed("id", "k")))  # a few sets
    other = F.when(F.col("k") == 0, F.col("text")).otherwise(F.regexp_replace("text", r"(\p{L}+)", F.concat(F.lit("$1q"), F.col("k").cast("string"))))
    return sets.select((F.col("doc_id") + F.col("k") * (top + 1)).alias("doc_id"), other.alias("text"))


def lengthened(docs: DataFrame, times: int) -> DataFrame:
    """The documents with texts of times as many words: each further part has other words."""
    parts = [F.coalesce("text", F.lit("")), *(F.regexp_replace(F.coalesce("text", F.lit("")), r"(\p{L}+)", f"$1q{k}") for k in range(1, times))]
    return docs.select("doc_id", F.concat_ws(" ", *parts).alias("text"))


def times_by_documents(spark: SparkSession, d: str) -> DataFrame:
    """(layout, documents, seconds): each layout is run once before it counts, so that code is compiled."""
    docs, rows = documents(spark, d), []
    sets = {k: materialize(multiplied(docs, k), "multiplied") for k in (1, 2, 4)}
    for layout in ("memory", "packed", "cells"):
        cfg = DedupConfig(layout=layout)
        work = lambda df, cfg=cfg: timed(lambda: run_out(candidates.banded(stored_bands(df, cfg))))
        work(sets[1])
        rows += [(layout, df.count(), work(df)) for df in sets.values()]
    return spark.createDataFrame(rows, "layout string, documents bigint, seconds double")


def times_by_words(spark: SparkSession, d: str) -> DataFrame:
    """(times, words, seconds) in memory."""
    docs, cfg, rows = documents(spark, d), DedupConfig(), []
    for k in (1, 1, 2, 4):  # the first run warms up
        df = materialize(lengthened(docs, k), "lengthened")
        words = df.agg(F.sum(F.size(F.split("text", " "))).alias("n")).first().n
        rows.append((k, words, timed(lambda df=df: run_out(candidates.banded(stored_bands(df, cfg))))))
    return spark.createDataFrame(rows[1:], "times int, words bigint, seconds double")


def forest_speedup(spark: SparkSession, grams: DataFrame, bands: DataFrame, edges: DataFrame, edge: float = 0.75, tree: float = 0.40) -> DataFrame:
    """One row: comparisons and seconds of workers that check all candidate pairs, and of those that fold the buckets into a bounded forest.

    Both work through the same buckets of a component of candidate pairs in one task, on sets in memory; a pair that has been compared is not
    compared again by either. Components share no bucket, so comparisons are those of one run over all; seconds are sums over the components.
    """

    def both(rows: pd.DataFrame, sets: pd.DataFrame) -> pd.DataFrame:
        whole = {x: np.unique(g) for x, g in zip(sets.doc_id, sets.grams, strict=True)}
        size = {x: len(g) for x, g in whole.items()}
        values, counts = np.unique(np.concatenate(list(whole.values())), return_counts=True)
        common = values[counts > 1]  # grams of one document alone are never shared
        own = {x: np.intersect1d(g, common, assume_unique=True) for x, g in whole.items()}
        lists = [g.doc_id.tolist() for _, g in rows.sort_values(["band_id", "value", "doc_id"]).groupby(["band_id", "value"], sort=False)]
        lists = [x for x in lists if len(x) > 1]
        made = [0]

        def similarity():
            known: dict[tuple[int, int], float] = {}

            def sim(x: int, y: int) -> float:
                key = (x, y) if x < y else (y, x)
                if key not in known:
                    made[0] += 1
                    shared = len(np.intersect1d(own[x], own[y], assume_unique=True))
                    known[key] = shared / max(1, size[x] + size[y] - shared)
                return known[key]

            return sim

        def check(sim) -> None:
            for m in lists:
                for i, x in enumerate(m):
                    for y in m[i + 1 :]:
                        sim(x, y)

        plain = timed(lambda: check(similarity()))
        pairs, made[0] = made[0], 0
        forest = timed(lambda: fold_buckets(lists, similarity(), edge, tree, keep=False))
        return pd.DataFrame([(pairs, made[0], plain, forest)], columns=["pairs", "forest_pairs", "seconds", "forest_seconds"])

    parts = components(edges).select(F.col("id").alias("doc_id"), F.col("component").alias("key"))
    left = bands.select("band_id", F.col("value").cast("string").alias("value"), "doc_id").join(parts, "doc_id")
    right = grams.join(parts, "doc_id").select(F.col("key").alias("part"), "doc_id", "grams")
    done = left.groupBy("key").cogroup(right.groupBy("part")).applyInPandas(lambda x, y: both(x, y), "pairs bigint, forest_pairs bigint, seconds double, forest_seconds double")
    return done.agg(*[F.sum(c).alias(c) for c in done.columns]).where("pairs IS NOT NULL").withColumn("speedup", F.col("seconds") / F.col("forest_seconds"))


def flush_times(spark: SparkSession, d: str, per_slice: int = 50) -> DataFrame:
    """(slice_id, docs, document_seconds, flush_seconds): the mean time to take in a document of a slice, and the time to write the slice.

    Each slice is packed by itself as it would be by a writer that holds one slice: values are appended for each document
    and written as arrays of all its bands when it is full.
    """
    docs, cfg = documents(spark, d), DedupConfig()
    slices = store.slice_ids(docs.select("doc_id"), store.slice_size(docs.count(), per_slice), ranked=True)
    rows = bands(docs, cfg).groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("band_id", "value"))).alias("x")).select("doc_id", F.col("x.value").alias("values")).join(slices, "doc_id")

    def write(p: pd.DataFrame) -> pd.DataFrame:
        held: list[list[int]] = [[] for _ in range(cfg.b)]

        def take(values) -> None:
            for k, v in enumerate(values):
                held[k].append(int(v))

        p = p.sort_values("doc_id")
        seconds = [timed(lambda v=v: take(v)) for v in p["values"]]
        flush = timed(lambda: pq.write_table(pa.table({"band_id": list(range(cfg.b)), "value": held}), pa.BufferOutputStream()))
        return pd.DataFrame([(int(p.slice_id.iloc[0]), len(p), float(np.mean(seconds)), flush)], columns=["slice_id", "docs", "document_seconds", "flush_seconds"])

    return rows.groupBy("slice_id").applyInPandas(write, "slice_id bigint, docs bigint, document_seconds double, flush_seconds double")


def held_bytes(df: DataFrame) -> int:
    """Bytes of a table in Spark's memory, as its cache measures them."""
    df = df.persist()
    try:
        df.count()
        return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    finally:
        df.unpersist()


def memory_use(spark: SparkSession, d: str) -> DataFrame:
    """(layout, bytes, model_bytes): what finding candidates holds at once: all bands, the cells of one band, or a slice while it is packed and then a band of arrays."""
    docs, cfg = documents(spark, d), DedupConfig()
    n, values = docs.count(), materialize(bands(docs, cfg), "bands")
    packed, directory = store.pack(values, store.slice_ids(docs, cfg.slices))
    slice_rows = values.join(store.slice_ids(docs, cfg.slices).where("slice_id = 0"), "doc_id").select("doc_id", "band_id", "value")
    per_slice = -(-n // cfg.slices)
    rows = [
        ("memory", held_bytes(values), 8 * n * cfg.b),
        ("cells", held_bytes(values.where("band_id = 0").select("doc_id", "value")), 8 * n),
        ("packed", held_bytes(slice_rows) + held_bytes(packed.where("band_id = 0").select("slice_id", "value")) + held_bytes(directory), 8 * (per_slice * cfg.b + n)),
    ]
    return spark.createDataFrame(rows, "layout string, bytes bigint, model_bytes bigint")
