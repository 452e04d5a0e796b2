"""Near duplicates among documents as they arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.config import DedupConfig
from neardup.functions.text import grams_of
from neardup.operators import banding, candidates, verify
from neardup.session import scratch_path


class BandStore:
    """Bands and sets of all documents that have arrived, a folder for each batch.

    What has arrived is read from the folders alone, so a store that is opened anew after a restart knows all batches; a batch
    that runs again overwrites its own folder and sees those before it only. A folder counts when its write has ended.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def batches(self, kind: str) -> list[int]:
        """Numbers of the batches that are written in full."""
        jvm = self.spark._jvm
        place = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}")
        fs = place.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(place):
            return []
        folders = [s.getPath() for s in fs.listStatus(place) if s.getPath().getName().startswith("batch=")]
        return sorted(int(p.getName().split("=")[1]) for p in folders if fs.exists(jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS")))

    def read(self, kind: str, before: int) -> DataFrame | None:
        known = [b for b in self.batches(kind) if b < before]
        return self.spark.read.parquet(*[f"{self.path}/{kind}/batch={b}" for b in known]) if known else None

    def add(self, rows: DataFrame, kind: str, batch: int) -> DataFrame:
        rows.write.mode("overwrite").parquet(f"{self.path}/{kind}/batch={batch}")
        return self.spark.read.parquet(f"{self.path}/{kind}/batch={batch}")


def arrive(store: BandStore, docs: DataFrame, batch: int, cfg: DedupConfig) -> DataFrame:
    """(a, b, jaccard) of a batch's documents with those before and with each other; the batch joins the store."""
    bands, sets = store.add(banding.bands(docs, cfg), "bands", batch), store.add(grams_of(docs, cfg, hashed=True), "sets", batch)
    old_bands, old_sets = store.read("bands", batch), store.read("sets", batch)
    pairs = candidates.banded(bands)
    if old_bands is not None:
        x, y = bands.select("band_id", "value", F.col("doc_id").alias("n")), old_bands.select("band_id", "value", F.col("doc_id").alias("o"))
        pairs = pairs.unionByName(x.join(y, ["band_id", "value"]).select(F.least("n", "o").alias("a"), F.greatest("n", "o").alias("b")).distinct())
        sets = sets.unionByName(old_sets)
    return verify.verified(pairs, sets, cfg.threshold)


def stream_pairs(spark: SparkSession, d: str, cfg: DedupConfig, files: int = 3) -> DataFrame:
    """All pairs of the documents table, which arrives as a stream of a few files, one for each batch."""
    rows = spark.read.parquet(f"{d.rstrip('/')}/documents.parquet").select("doc_id", "text")
    source, out, marks = (scratch_path(spark, x) for x in ("arrivals", "stream-pairs", "stream-marks"))
    rows.repartition(files, "doc_id").write.parquet(source)
    store = BandStore(spark, scratch_path(spark, "band-store"))

    def take(batch: DataFrame, n: int) -> None:
        arrive(store, batch, n, cfg).write.mode("overwrite").parquet(f"{out}/batch={n}")

    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(source)
    stream.writeStream.option("checkpointLocation", marks).trigger(availableNow=True).foreachBatch(take).start().awaitTermination()
    return spark.read.schema("a bigint, b bigint, jaccard double").parquet(out).select("a", "b", "jaccard")
