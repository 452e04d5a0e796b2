"""Windows, sessions and duplicates of the event stream. Each query is run to its end over the files at hand and gives its sink's rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.session import scratch_path


def event_stream(spark: SparkSession, d: str) -> DataFrame:
    """The events table as a stream of its files, with a watermark."""
    path = f"{d.rstrip('/')}/events.parquet"
    schema = spark.read.parquet(path).schema
    # The table may be one file: its folder is watched for that name alone.
    folder, name = path.rsplit("/", 1)
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", "false").parquet(f"{folder}/{name[:-len('.parquet')]}*.parquet")
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "10 minutes")


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Writes all that is at hand through foreachBatch, once for each batch even after a restart, and reads it back."""
    spark = stream.sparkSession
    out, marks = scratch_path(spark, "stream"), scratch_path(spark, "stream-marks")

    def write(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={n}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", marks).trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def windowed(spark: SparkSession, d: str, width: str, slide: str | None) -> DataFrame:
    """(start, event_type, n, total) of tumbling or sliding windows; complete mode, so the last windows come out too."""
    e = event_stream(spark, d)
    agg = e.groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    rows = run_to_end(agg.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n", F.round("total", 4).alias("total")), "complete")
    return rows.select("start", "event_type", "n", "total")


def sessions(spark: SparkSession, d: str, gap: str) -> DataFrame:
    """(user_id, start, n) of runs of a user's events with less than the gap between them."""
    e = event_stream(spark, d)
    agg = e.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return run_to_end(agg.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n"), "complete").select("user_id", "start", "n")


def deduplicated(spark: SparkSession, d: str) -> DataFrame:
    """(user_id, event_type, n): events of one minute, user and type count once."""
    e = event_stream(spark, d).withColumn("minute", F.date_trunc("minute", "ts"))
    once = e.dropDuplicates(["user_id", "event_type", "minute"])
    return run_to_end(once.select("user_id", "event_type", "minute")).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


def user_state(spark: SparkSession, d: str) -> DataFrame:
    """(user_id, n, high): events and highest value of each user, kept as state and put out whenever a user's state changes."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, batches, state):
        n, high = state.get if state.exists else (0, float("-inf"))
        for p in batches:
            n, high = n + len(p), max(high, p["value"].max())
        state.update((int(n), float(high)))
        yield pd.DataFrame({"user_id": [key[0]], "n": [int(n)], "high": [float(high)]})

    e = event_stream(spark, d).select("user_id", "value").where("value IS NOT NULL")
    kept = e.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, n bigint, high double", "n bigint, high double", "update", GroupStateTimeout.NoTimeout)
    # A user may be put out in several batches: the one with most events is the last.
    return run_to_end(kept, "update").groupBy("user_id").agg(F.max("n").alias("n"), F.max("high").alias("high"))


def once_within_watermark(spark: SparkSession, d: str) -> DataFrame:
    """(events, distinct_events): rows of the stream, and rows with an event_id not seen within the watermark's delay."""
    e = event_stream(spark, d)
    once = run_to_end(e.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))
    return once.agg(F.count("*").alias("kept"), F.countDistinct("event_id").alias("distinct_events"))


def late_rows(spark: SparkSession, d: str) -> DataFrame:
    """One row (rows, late): the newer half of the events arrives first, and how many of the others come too late for the watermark.

    The engine counts the late rows itself, in the progress of the operator that drops them.
    """
    rows = spark.read.parquet(f"{d.rstrip('/')}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    middle = rows.agg(F.min("ts").cast("double").alias("lo"), F.max("ts").cast("double").alias("hi")).first()
    newer = F.col("ts").cast("double") * 2 >= middle.lo + middle.hi
    source, out, marks = (scratch_path(spark, x) for x in ("late-events", "stream", "stream-marks"))
    late = 0
    # The query ends after the first half and starts again for the other: the watermark comes back from the checkpoint.
    for part in (rows.where(newer), rows.where(~newer)):
        part.coalesce(1).write.mode("append").parquet(source)
        stream = spark.readStream.schema(rows.schema).parquet(source).withWatermark("ts", "10 minutes")
        once = stream.dropDuplicatesWithinWatermark(["event_id"])
        query = once.writeStream.option("checkpointLocation", marks).trigger(availableNow=True).foreachBatch(lambda batch, n: batch.write.mode("overwrite").parquet(f"{out}/batch={n}")).start()
        query.awaitTermination()
        late += sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])
    return rows.agg(F.count("*").alias("rows")).withColumn("late", F.lit(late).cast("bigint"))
