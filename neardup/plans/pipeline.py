"""A whole run: signatures, bands in memory or in a store, candidates, exact check, clusters."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.config import DedupConfig
from neardup.functions.text import grams_of
from neardup.operators import candidates, cluster, exact, store, verify
from neardup.operators.banding import bands as bands_of
from neardup.session import materialize, scratch_path


@dataclass
class Run:
    """What a run leaves behind."""

    bands: DataFrame
    candidates: DataFrame
    pairs: DataFrame


def stored_bands(df: DataFrame, cfg: DedupConfig, path: str | None = None) -> DataFrame:
    """Band values by way of the layout of cfg."""
    made, spark = bands_of(df, cfg), df.sparkSession
    if cfg.layout == "memory":
        return materialize(made, "bands")
    path = path or scratch_path(spark, cfg.layout)
    if cfg.layout == "cells":
        store.write_cells(made, path)
        return store.read_cells(spark, path)
    store.write_packed(materialize(made, "bands"), store.slice_ids(df, cfg.slices), path)
    return store.read_packed(spark, path)


def run(df: DataFrame, cfg: DedupConfig, path: str | None = None, collapse: bool = True, size_filter: bool = True) -> Run:
    """Pairs above cfg.threshold.

    With collapse copies of a text go through as one document: pairs are found among one document for each text and
    expanded at the end, so K copies cost K rows and not K * K pairs in each band. With size_filter pairs whose sets' sizes
    can't be alike enough are left out in the join on bands. Bands and candidates are those of the documents that go through.
    """
    docs = materialize(exact.representatives(df), "texts") if collapse else df
    bands = stored_bands(docs, cfg, path)
    grams = materialize(grams_of(docs, cfg, hashed=True), "grams")
    sizes = grams.select("doc_id", F.size("grams").alias("n_grams"))
    found = materialize(candidates.size_filtered(bands, sizes, cfg.threshold) if size_filter else candidates.banded(bands), "candidates")
    pairs = verify.verified(found, verify.sets_of(found, grams), cfg.threshold)
    if collapse:
        real = sizes.where("n_grams > 0").select(F.col("doc_id").alias("rep"))
        pairs = exact.expand(pairs, exact.exact_groups(df).join(real, "rep", "left_semi"))
    return Run(bands, found, pairs)


def near_duplicates(df: DataFrame, cfg: DedupConfig | None = None) -> DataFrame:
    return run(df, cfg or DedupConfig()).pairs


def _with_copies(found: DataFrame, df: DataFrame) -> DataFrame:
    """Gives copies of a text the cluster of the one that went through; rows without a text stand alone."""
    groups = exact.exact_groups(df).withColumnRenamed("doc_id", "copy")
    named = groups.join(found.withColumnRenamed("doc_id", "rep"), "rep").select(F.col("copy").alias("doc_id"), "cluster_id", "root", "bound")
    alone = df.where("text IS NULL").select("doc_id", F.col("doc_id").alias("cluster_id"), F.col("doc_id").alias("root"), F.lit(1.0).alias("bound"))
    return named.unionByName(alone)


def clusters(df: DataFrame, cfg: DedupConfig | None = None) -> DataFrame:
    """(doc_id, cluster_id, root, bound) of documents with distinct ids.

    One document for each text is clustered, and its copies, which are as alike to the others as it is, join it.
    """
    cfg = cfg or DedupConfig()
    docs = materialize(exact.representatives(df), "texts")
    return _with_copies(_clustered(docs, stored_bands(docs, cfg), materialize(grams_of(docs, cfg, hashed=True), "grams"), cfg), df)


def _clustered(docs: DataFrame, bands: DataFrame, grams: DataFrame, cfg: DedupConfig) -> DataFrame:
    if cfg.mode == "rounds":
        edges = materialize(verify.verified(candidates.banded(bands), grams, cfg.edge_threshold), "edges")
        found = cluster.rounds(edges, grams, cfg.edge_threshold, cfg.tree_threshold)
        names = found.groupBy("root").agg(F.min("doc_id").alias("cluster_id"))
        rest = docs.select("doc_id").join(found, "doc_id", "left_anti").select("doc_id", F.col("doc_id").alias("cluster_id"), F.col("doc_id").alias("root"), F.lit(1.0).alias("bound"))
        return found.join(names, "root").select("doc_id", "cluster_id", "root", "bound").unionByName(rest)
    return cluster.assignments(cluster.bounded_clusters(bands, grams, cfg.edge_threshold, cfg.tree_threshold, cfg.refresh), docs)


def recluster(spark: SparkSession, path: str, grams: DataFrame, docs: DataFrame, cfg: DedupConfig) -> DataFrame:
    """The second step again with other thresholds or another mode, from stored cells of one document for each text: nothing is hashed anew."""
    return _with_copies(_clustered(exact.representatives(docs), store.read_cells(spark, path), grams, cfg), docs)
