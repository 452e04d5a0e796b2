"""Consecutive ranks over a whole table without a task that sees all of it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from neardup.session import materialize


def ranked(df: DataFrame, key: str, name: str = "rank") -> DataFrame:
    """df with the number of rows before each one in order of key, which must tell rows apart.

    Rows are dealt by ranges of key and numbered within their range; only the sizes of ranges, one row for each
    partition, are summed in one place.
    """
    part, own = f"{name}_part", f"{name}_own"
    dealt = df.repartitionByRange(key).sortWithinPartitions(key).withColumn(own, F.monotonically_increasing_id())
    # The id has the partition's number above 33 bits and the row's number in it below.
    rows = materialize(dealt.withColumn(part, F.shiftright(own, 33)).withColumn(own, F.col(own).bitwiseAND(F.lit((1 << 33) - 1))), "ranked")
    before = Window.orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    sizes = rows.groupBy(part).agg(F.count("*").alias("n")).select(part, F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    return rows.join(F.broadcast(sizes), part).withColumn(name, (F.col("before") + F.col(own)).cast("bigint")).drop(part, own, "before")
