"""Joins on keys of which a few may hold a large share of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.session import materialize

#: A key is heavy if it has more than one in so many of the rows that are counted; fewer keys than that can be heavy.
HEAVY_KEYS = 1_000


def heavy_limit(counts: DataFrame, n: str = "n", heavy_keys: int = HEAVY_KEYS) -> int:
    """The most rows that a key has without being heavy."""
    total = counts.agg(F.sum(n)).first()[0] or 0
    return max(1, int(total) // heavy_keys)


def join_counted(rows: DataFrame, counts: DataFrame, keys: list[str], how: str = "inner", n: str = "n", heavy_keys: int = HEAVY_KEYS) -> DataFrame:
    """rows joined ('inner' or 'left_semi') with counts, which has one row for each key and in n how many of rows have it.

    Heavy keys meet their rows where these lie, by a broadcast of fewer than heavy_keys rows of counts at any size of the
    input; all others go by a sort-merge join in which no key has more than one row in heavy_keys. Rows
    with a key that counts lacks are dropped, as in any join. counts is read several times: give a written table.
    """
    limit = heavy_limit(counts, n, heavy_keys)
    heavy, light = counts.where(F.col(n) > limit), counts.where(F.col(n) <= limit)
    few = rows.join(F.broadcast(heavy), keys, how)
    rest = rows.join(F.broadcast(heavy.select(*keys)), keys, "left_anti").join(light.hint("merge"), keys, how)
    return few.unionByName(rest)


def repeated(rows: DataFrame, keys: list[str]) -> DataFrame:
    """The rows whose key occurs more than once; rows are read several times."""
    counts = materialize(rows.groupBy(*keys).agg(F.count("*").alias("n")).where("n > 1"), "repeated-keys")
    return join_counted(rows, counts, keys, "left_semi")
