"""Use of clusters: removing redundant documents, and what the members of a cluster share."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def deduplicate(df: DataFrame, clusters: DataFrame, keep: str = "first", labels: DataFrame | None = None) -> DataFrame:
    """The rows of df that stand for their cluster, with all columns.

    keep: 'first' lowest id, 'longest' most characters, 'root' the cluster's root, 'best_quality' highest label; ties go to the
    lowest id. Documents in no cluster stay.
    """
    named = df.select("doc_id", F.length("text").alias("chars")).join(clusters, "doc_id", "left").withColumn("cluster_id", F.coalesce("cluster_id", "doc_id"))
    if keep == "root":
        chosen = named.where(F.coalesce("root", "doc_id") == F.col("doc_id")).select("doc_id")
    else:
        if keep == "best_quality":
            named = named.join(labels.select("doc_id", "quality"), "doc_id", "left")
        rank = {"first": F.lit(0), "longest": F.coalesce("chars", F.lit(0)), "best_quality": F.coalesce("quality", F.lit(-1)) if keep == "best_quality" else None}[keep]
        best = named.groupBy("cluster_id").agg(F.max_by("doc_id", F.struct(rank.alias("r"), (-F.col("doc_id")).alias("i"))).alias("doc_id"))
        chosen = best.select("doc_id")
    return df.join(chosen, "doc_id", "left_semi")


def common_grams(clusters: DataFrame, exploded: DataFrame, share: float = 1.0) -> DataFrame:
    """(cluster_id, gram, members): grams that at least this share of a cluster's two or more members have."""
    sizes = clusters.groupBy("cluster_id").agg(F.count("*").alias("n")).where("n > 1")
    rows = exploded.join(clusters.select("doc_id", "cluster_id"), "doc_id").groupBy("cluster_id", "gram").agg(F.count("*").alias("members"))
    return rows.join(sizes, "cluster_id").where(F.col("members") >= share * F.col("n")).select("cluster_id", "gram", "members")
