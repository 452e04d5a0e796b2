"""Session helpers: settings for own sessions, shared scratch space, shipping of the package."""

from __future__ import annotations

import atexit
import gc
import os
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_ROOT = Path(__file__).resolve().parent
_SHIPPED = "neardup.shipped"
_LOCAL: dict[str, str] = {}
_WRITTEN: dict[str, list[str]] = {}


def get_session(cores: str = "*", shuffle_partitions: int = 8) -> SparkSession:
    """A local session for tests and benches; on a cluster the caller brings its own."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", os.environ.get("NEARDUP_DRIVER_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def shared_root(spark: SparkSession) -> str:
    """Folder that driver and executors share: spark.checkpoint.dir, or an own one where that is unset."""
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        _LOCAL[app] = tempfile.mkdtemp(prefix="neardup-")
        atexit.register(shutil.rmtree, _LOCAL[app], ignore_errors=True)
    return _LOCAL[app]


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path under the shared folder; it is deleted when this process ends, or by release()."""
    path = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
    app = spark.sparkContext.applicationId
    if app not in _WRITTEN:
        _WRITTEN[app] = []
        atexit.register(_clean, spark, app)
    _WRITTEN[app].append(path)
    return path


def _delete(spark: SparkSession, path: str) -> None:
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def _clean(spark: SparkSession, app: str) -> None:
    """Deletes what is left at the end, as far as the session still lives."""
    if spark._jsc is None or spark.sparkContext._jsc is None:
        return
    for path in _WRITTEN.pop(app, []):
        try:
            _delete(spark, path)
        except Exception:  # the JVM may be gone by now, and with it the way to delete
            return


def materialize(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Writes df to the shared folder and reads it again: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def release(*tables: DataFrame) -> None:
    """Deletes what materialize() wrote for tables that nothing reads any more."""
    for t in tables:
        path = getattr(t, "_scratch_path", None)
        if path is not None:
            _delete(t.sparkSession, path)
            _WRITTEN[t.sparkSession.sparkContext.applicationId].remove(path)
            t._scratch_path = None


def release_shuffles(spark: SparkSession) -> None:
    """Deletes the shuffle files of jobs that are done and that no table refers to: Spark does so once the driver's collector has found them."""
    gc.collect()
    spark._jvm.System.gc()


def ship_package(spark: SparkSession) -> None:
    """Makes this package importable on executors that only have Spark's own Python path."""
    sc = spark.sparkContext
    if getattr(sc, "_neardup_shipped", False):
        return
    folder = tempfile.mkdtemp(prefix="neardup-zip-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    target = os.path.join(folder, "neardup_package.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(_ROOT.rglob("*.py")):
            z.write(p, str(p.relative_to(_ROOT.parent)))
    sc.addPyFile(target)
    sc._neardup_shipped = True
