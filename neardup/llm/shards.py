"""Operator 7: size-tiered compaction of immutable shards under a versioned manifest.

A store is a folder: data/ has Parquet files that are never changed, manifests/v<N> lists the files that make
up version N. An append writes its rows as they come, a small shard for each task, and commits a version with
the new files added. Compaction puts shards into tiers by size (each tier FANOUT times the one below),
packs the shards of every tier that has FANOUT of them into files of about the target size, and
commits a version with these instead. A commit renames a finished manifest into place and
fails if that version exists, so readers see all of a version or nothing, and of two writers
one has to try again. Only DataFrame and SQL functions touch rows.

Cases: rows, nulls, repeated rows and all columns are kept as they are; an append without rows adds a version
without files; a file of the target size or more stays as it is; a store without a version reads as an error.
Work of a failed task or job leaves files that no manifest names; vacuum removes them when they are old enough to belong to
no append or merge that still runs. Further columns, whatever their names, are kept: none is added to the rows.
"""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

TARGET_BYTES = 128 << 20
BASE_BYTES = 1 << 20
FANOUT = 4
ROUNDS = 8
#: Files that no manifest names are deleted when they are so old; no append or merge may take longer.
VACUUM_SECONDS = 7 * 24 * 3600
_MANIFEST = "path string, bytes bigint, n_rows bigint"


class CommitConflict(RuntimeError):
    """Another writer has committed this version."""


class ShardStore:
    def __init__(self, spark: SparkSession, path: str, schema: str | None = None):
        self.spark, self.path, self.schema = spark, path.rstrip("/"), schema
        self._jvm = spark._jvm
        self._conf = spark._jsc.hadoopConfiguration()

    def _hadoop(self, path: str):
        p = self._jvm.org.apache.hadoop.fs.Path(path)
        return p, p.getFileSystem(self._conf)

    def versions(self) -> list[int]:
        p, fs = self._hadoop(f"{self.path}/manifests")
        if not fs.exists(p):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(p)]
        return sorted(int(n[1:]) for n in names if n.startswith("v"))

    def manifest(self, version: int | None = None) -> DataFrame:
        """Rows (path, bytes, n_rows) of the files of a version, the latest by default."""
        known = self.versions()
        if version is None and not known:
            return self.spark.createDataFrame([], _MANIFEST)
        return self.spark.read.schema(_MANIFEST).parquet(f"{self.path}/manifests/v{known[-1] if version is None else version}")

    def commit(self, files: DataFrame, base: int) -> int:
        """Makes files the version after base, or raises CommitConflict."""
        waiting, target = f"{self.path}/manifests/_wait-{uuid.uuid4().hex}", f"{self.path}/manifests/v{base + 1}"
        files.select("path", "bytes", "n_rows").write.parquet(waiting)
        source, fs = self._hadoop(waiting)
        place, _ = self._hadoop(target)
        context = self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.makeQualified(source).toUri(), self._conf)
        kind = getattr(self._jvm.org.apache.hadoop.fs, "Options$Rename")
        try:
            context.rename(fs.makeQualified(source), fs.makeQualified(place), self.spark._sc._gateway.new_array(kind, 0))
        except Exception as e:
            fs.delete(source, True)
            if fs.exists(place):
                raise CommitConflict(f"version {base + 1} exists") from e
            raise
        return base + 1

    def _files_of(self, folder: str, schema) -> DataFrame:
        """(path, bytes, n_rows) of the files that a job has written."""
        seen = self.spark.read.schema(schema).parquet(folder).select(F.col("_metadata.file_path").alias("path"), F.col("_metadata.file_size").alias("bytes"))
        return seen.groupBy("path", "bytes").agg(F.count("*").alias("n_rows"))

    def append(self, rows: DataFrame) -> int:
        """Writes rows as small shards without a shuffle and commits them; tries again if another writer was first."""
        folder = f"{self.path}/data/append-{uuid.uuid4().hex}"
        rows.write.option("compression", "zstd").parquet(folder)
        self.schema = rows.schema
        new = self._files_of(folder, rows.schema)
        for _ in range(20):
            base = (self.versions() or [0])[-1]
            try:
                return self.commit(self.manifest().unionByName(new), base)
            except CommitConflict:
                continue
        raise CommitConflict("too many writers")

    def plan(self, target: int = TARGET_BYTES, fanout: int = FANOUT, base: int = BASE_BYTES) -> DataFrame:
        """(path, bytes, n_rows, tier, bin): shards to merge, by the file that they go to. Windows run over the manifest alone."""
        tier = F.floor(F.log(float(fanout), F.greatest(F.lit(1.0), F.col("bytes") / base))).cast("int")
        small = self.manifest().where(F.col("bytes") < target).withColumn("tier", tier)
        full = small.groupBy("tier").agg(F.count("*").alias("shards")).where(F.col("shards") >= fanout).select("tier")
        order = Window.partitionBy("tier").orderBy("bytes", "path").rowsBetween(Window.unboundedPreceding, -1)
        binned = small.join(full, "tier").withColumn("at", F.floor(F.coalesce(F.sum("bytes").over(order), F.lit(0)) / target))
        return binned.withColumn("bin", F.dense_rank().over(Window.orderBy("tier", "at")) - 1).drop("at")

    def compact_once(self, target: int = TARGET_BYTES, fanout: int = FANOUT) -> int | None:
        """One round of merging; the new version, or None if no tier is full."""
        base = self.versions()[-1]
        plan = self.plan(target, fanout).select("path", "bytes", "n_rows", "bin").persist()
        try:
            paths = [r.path for r in plan.select("path").collect()]
            if not paths:
                return None
            bins = plan.agg(F.max("bin")).first()[0] + 1
            schema = self._schema()
            rows = self.spark.read.schema(schema).parquet(*paths).withColumn("_path", F.col("_metadata.file_path"))
            merged = rows.join(plan.select(F.col("path").alias("_path"), "bin"), "_path").repartitionById(bins, F.col("bin").cast("int"))
            folder = f"{self.path}/data/merge-{uuid.uuid4().hex}"
            merged.select(*[f.name for f in schema]).write.option("compression", "zstd").parquet(folder)
            rest = self.manifest().join(plan.select("path"), "path", "left_anti")
            return self.commit(rest.unionByName(self._files_of(folder, schema)), base)
        finally:
            plan.unpersist()

    def compact(self, target: int = TARGET_BYTES, fanout: int = FANOUT, rounds: int = ROUNDS) -> int:
        """Merges until no tier below the target is full; gives the version."""
        for _ in range(rounds):
            if self.compact_once(target, fanout) is None:
                break
        return self.versions()[-1]

    def _schema(self):
        if self.schema is None:
            self.schema = self.read().schema
        return self.schema

    def read(self, version: int | None = None) -> DataFrame:
        """All rows of a version, the latest by default."""
        if not self.versions():
            raise FileNotFoundError(f"no version in {self.path}")
        paths = [r.path for r in self.manifest(version).select("path").collect()]
        if paths:
            return self.spark.read.schema(self.schema).parquet(*paths) if self.schema else self.spark.read.parquet(*paths)
        if self.schema is None:
            raise FileNotFoundError("the version has no files and no schema is known")
        return self.spark.createDataFrame([], self.schema)

    def vacuum(self, keep: int = 1, older_than: float = VACUUM_SECONDS) -> int:
        """Deletes data files that none of the last versions names and that are older than so many seconds, and older manifests; gives the number of files deleted.

        The age guards files of an append or merge that hasn't committed yet.
        """
        known = self.versions()
        latest = (time.time() - older_than) * 1000
        named = [self.manifest(v).select(F.substring_index("path", "/", -2).alias("name")) for v in known[-keep:]]
        p, fs = self._hadoop(f"{self.path}/data")
        there = [(f"{folder.getPath().getName()}/{f.getPath().getName()}",) for folder in (fs.listStatus(p) if fs.exists(p) else []) for f in fs.listStatus(folder.getPath()) if f.getPath().getName().endswith(".parquet") and f.getModificationTime() <= latest]
        found = self.spark.createDataFrame(there, "name string")
        for names in named:
            found = found.join(names, "name", "left_anti")
        gone = 0
        for r in found.toLocalIterator():
            q, _ = self._hadoop(f"{self.path}/data/{r.name}")
            gone += bool(fs.delete(q, False))
        for v in known[:-keep]:
            q, _ = self._hadoop(f"{self.path}/manifests/v{v}")
            fs.delete(q, True)
        return gone


def arrivals(docs: DataFrame, n: int = 3) -> list[DataFrame]:
    """docs in n parts by ranges of doc_id, as arrivals that follow each other; null ids come first."""
    edges = docs.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)], 10_000).alias("q")).first().q or []
    edges, d = sorted(set(edges)), F.col("doc_id")
    parts, low = [], None
    for e in edges:
        parts.append(docs.where((d <= e) | d.isNull() if low is None else (d > low) & (d <= e)))
        low = e
    return [*parts, docs.where(d > low) if low is not None else docs]


def sharded_digests(docs: DataFrame, path: str, target: int = TARGET_BYTES, fanout: int = FANOUT) -> DataFrame:
    """Appends docs with all columns in arrivals, compacts, and reads (doc_id, n_bytes, text_md5) from the committed version."""
    store = ShardStore(docs.sparkSession, path)
    for part in arrivals(docs):
        store.append(part)
    store.compact(target, fanout)
    return store.read().select("doc_id", F.octet_length("text").cast("bigint").alias("n_bytes"), F.md5("text").alias("text_md5"))
