"""Accuracy measures of candidate pairs and quality measures of clusters."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _n(df: DataFrame, name: str) -> DataFrame:
    return df.agg(F.count("*").alias(name))


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: true pairs, found ones, and their share (1 without true pairs)."""
    hit = truth.select("a", "b").join(found.select("a", "b", F.lit(1).alias("hit")), ["a", "b"], "left")
    return hit.agg(F.count("*").alias("true_pairs"), F.count("hit").alias("found_pairs")).withColumn("recall", F.when(F.col("true_pairs") > 0, F.col("found_pairs") / F.col("true_pairs")).otherwise(F.lit(1.0)))


def false_candidates(cand: DataFrame, truth: DataFrame) -> DataFrame:
    """Candidates that aren't true pairs."""
    return cand.join(truth.select("a", "b"), ["a", "b"], "left_anti")


def false_negatives(cand: DataFrame, truth: DataFrame) -> DataFrame:
    """True pairs that aren't candidates."""
    return truth.join(cand.select("a", "b"), ["a", "b"], "left_anti")


def candidate_ratio(cand: DataFrame, n_docs: int) -> DataFrame:
    total = n_docs * (n_docs - 1) // 2
    return _n(cand, "candidates").withColumn("all_pairs", F.lit(total).cast("bigint")).withColumn("ratio", F.col("candidates") / F.greatest(F.lit(1), F.col("all_pairs")))


def estimate_error(pairs: DataFrame) -> DataFrame:
    """Mean and largest error of estimates against jaccard."""
    e = F.abs(F.col("estimate") - F.col("jaccard"))
    return pairs.agg(F.count("*").alias("pairs"), F.round(F.avg(e), 6).alias("mean_error"), F.round(F.max(e), 6).alias("max_error"))


def pairs_excluded(n_pairs: int, compared: DataFrame) -> DataFrame:
    """Comparisons that clustering saves: all candidate pairs less those compared, raw and distinct."""
    both = compared.agg(F.count("*").alias("compared"), F.countDistinct(F.least("a", "b"), F.greatest("a", "b")).alias("compared_distinct"))
    return both.withColumn("candidates", F.lit(n_pairs).cast("bigint")).withColumn("excluded", F.col("candidates") - F.col("compared_distinct")).withColumn("excluded_raw", F.col("candidates") - F.col("compared"))


def with_clusters(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """(a, b, jaccard, x, y): pairs with the clusters of both ends; a document without a cluster is its own."""
    ca, cb = clusters.select(F.col("doc_id").alias("a"), F.col("cluster_id").alias("ca")), clusters.select(F.col("doc_id").alias("b"), F.col("cluster_id").alias("cb"))
    return edges.join(ca, "a", "left").join(cb, "b", "left").select("a", "b", "jaccard", F.coalesce("ca", "a").alias("x"), F.coalesce("cb", "b").alias("y"))


def all_inside(clusters: DataFrame, grams: DataFrame) -> DataFrame:
    """Scored pairs of all members of each cluster, whether candidates or not."""
    from neardup.operators.verify import scored

    left, right = clusters.select("cluster_id", F.col("doc_id").alias("a")), clusters.select("cluster_id", F.col("doc_id").alias("b"))
    return scored(left.join(right, "cluster_id").where("a < b").select("a", "b"), grams)


def inside_categories(clusters: DataFrame, grams: DataFrame, edge: float, tree: float, together: int = 1024) -> DataFrame:
    """same_high, same_mid and same_low of pair_categories() over all pairs inside clusters, which are counted where blocks of documents meet and never become rows."""
    from neardup.operators.ranks import ranked
    from neardup.operators.verify import Counted

    many = clusters.groupBy("cluster_id").agg(F.count("*").alias("n")).where("n > 1").select("cluster_id")
    members = clusters.select("doc_id", "cluster_id").join(many, "cluster_id").withColumn("key", F.struct("cluster_id", "doc_id"))
    place = ranked(members, "key").select("doc_id", "cluster_id", F.floor(F.col("rank") / F.lit(together)).alias("k"))
    ends = place.groupBy("cluster_id").agg(F.min("k").alias("low"), F.max("k").alias("high"))
    met = place.join(ends, "cluster_id").select("doc_id", "cluster_id", "k", F.explode(F.sequence("low", "high")).alias("o"))
    rows = met.join(grams, "doc_id").select(F.least("k", "o").alias("x"), F.greatest("k", "o").alias("y"), "k", "cluster_id", "doc_id", "grams")

    def count(p: pd.DataFrame) -> pd.DataFrame:
        x, y, out = int(p.x.iloc[0]), int(p.y.iloc[0]), np.zeros(3, np.int64)
        for _, c in p.groupby("cluster_id"):
            left, right = c[c.k == x], c[c.k == y]
            counted, ids = Counted([np.unique(g) for g in left.grams]), left.doc_id.to_numpy()
            for d, g in zip(right.doc_id, right.grams, strict=True):
                s = counted.jaccard(np.unique(g))
                s = s[ids < d] if x == y else s
                low = int((s < tree - 1e-12).sum())
                high = int((s > edge).sum())
                out += (high, len(s) - high - low, low)
        return pd.DataFrame([out.tolist()], columns=["same_high", "same_mid", "same_low"])

    parts = rows.groupBy("x", "y").applyInPandas(count, "same_high bigint, same_mid bigint, same_low bigint")
    return parts.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("same_high", "same_mid", "same_low")])


def pair_categories(edges: DataFrame, clusters: DataFrame, edge: float, tree: float) -> DataFrame:
    """One row of counts: pairs above edge in one cluster and in two, and pairs in one cluster from tree to edge and below tree."""
    p = with_clusters(edges, clusters)
    same, s = F.col("x") == F.col("y"), F.col("jaccard")
    return p.agg(
        F.count(F.when(same & (s > edge), 1)).alias("same_high"),
        F.count(F.when(~same & (s > edge), 1)).alias("diff_high"),
        F.count(F.when(same & (s <= edge) & (s >= tree - 1e-12), 1)).alias("same_mid"),
        F.count(F.when(same & (s < tree - 1e-12), 1)).alias("same_low"),
    ).withColumn("share_high", F.round(F.col("same_high") / F.greatest(F.lit(1), F.col("same_high") + F.col("same_mid") + F.col("same_low")), 6))


def modularity_parts(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """(cluster_id, part): what each cluster adds to the weighted modularity."""
    p = with_clusters(edges, clusters)
    inside = p.where("x = y").groupBy(F.col("x").alias("cluster_id")).agg(F.sum("jaccard").alias("inner"))
    ends = p.select(F.col("x").alias("cluster_id"), "jaccard").unionByName(p.select(F.col("y").alias("cluster_id"), "jaccard"))
    degree = ends.groupBy("cluster_id").agg(F.sum("jaccard").alias("degree"))
    total = p.agg((2 * F.sum("jaccard")).alias("m2"))
    both = degree.join(inside, "cluster_id", "left").crossJoin(F.broadcast(total))  # one row
    return both.select("cluster_id", (2 * F.coalesce("inner", F.lit(0.0)) / F.col("m2") - F.pow(F.col("degree") / F.col("m2"), 2)).alias("part"))


def modularity(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    return modularity_parts(edges, clusters).agg(F.round(F.coalesce(F.sum("part"), F.lit(0.0)), 6).alias("modularity"))


def cluster_stats(clusters: DataFrame) -> DataFrame:
    """One row: clusters of two or more, the largest, single documents, documents in clusters."""
    sizes = clusters.groupBy("cluster_id").agg(F.count("*").alias("n"))
    many = F.when(F.col("n") > 1, F.col("n"))
    return sizes.agg(F.count(many).alias("clusters"), F.coalesce(F.max(many), F.lit(0)).alias("largest"), F.count(F.when(F.col("n") == 1, 1)).alias("singles"), F.coalesce(F.sum(many), F.lit(0)).alias("clustered"))


def size_histogram(clusters: DataFrame) -> DataFrame:
    return clusters.groupBy("cluster_id").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("clusters"))


def bound_violations(clusters: DataFrame, grams: DataFrame, tree: float) -> DataFrame:
    """One row: pairs in one cluster below the tree threshold, and members less like their root than its bound. Both are 0."""
    from neardup.operators.verify import scored

    low = all_inside(clusters, grams).where(F.col("jaccard") < tree - 1e-9).select(F.lit(1).alias("x"))
    to_root = scored(clusters.where("doc_id <> root").select(F.col("doc_id").alias("a"), F.col("root").alias("b")), grams)
    under = to_root.join(clusters.select(F.col("doc_id").alias("a"), "bound"), "a").where(F.col("jaccard") < F.col("bound") - 1e-9).select(F.lit(1).alias("x"))
    return low.agg(F.count("*").alias("low_pairs")).crossJoin(under.agg(F.count("*").alias("root_violations")))  # one row each
