"""Connected components of edge lists."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.session import materialize, release

MOST_ROUNDS = 60


def _lowest(stars: DataFrame) -> DataFrame:
    return stars.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low"))


def _large_star(edges: DataFrame) -> DataFrame:
    """Joins each node's larger neighbours to the lowest of its neighbours and itself."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return both.join(_lowest(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Joins each node and its smaller neighbours to the lowest of them; edges come with u > v."""
    joined = edges.join(_lowest(edges), "u")
    moved = joined.where("v <> low").select(F.col("v").alias("u"), F.col("low").alias("v"))
    return moved.unionByName(joined.select("u", F.col("low").alias("v"))).where("u <> v").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(id, component) for each node of an edge: component is the lowest id that its edges reach.

    Alternates two star contractions (a published method) until the stars stand still: the rounds grow
    with the logarithm of the nodes. Every round is written to the shared folder, partial minima keep hubs
    from being one task's burden, and joins on hubs can be split. No edges give no rows.
    """
    stars = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    stars, seen = materialize(stars, "stars"), None
    for _ in range(MOST_ROUNDS):
        before, stars = stars, materialize(_small_star(_large_star(stars)), "stars")
        release(before)
        now = stars.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    ids = stars.select(F.col("u").alias("id"), F.col("v").alias("component"))
    return ids.unionByName(stars.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
