"""Where intermediate and final tables are kept, and how code reaches executors."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

#: Used only where the session names no shared folder (single-machine tests).
LOCAL_FALLBACK = "/tmp/checkpoints"

#: Rows of one Arrow batch: whole texts travel in it, so it must be small.
BATCH_ROWS = 1000

#: Whether Spark deletes the shuffle files of a query when it ends.
CLEAN_UP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_made: dict[str, str] = {}
_shipped: set[str] = set()


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir`` of the session, else a local one."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        root = LOCAL_FALLBACK
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def new_folder(spark: SparkSession, tag: str) -> str:
    """A fresh path under the shared folder; all such paths of an application go when it ends."""
    app = spark.sparkContext.applicationId
    if app not in _made:
        _made[app] = f"{shared_root(spark)}/lexnorm-{uuid.uuid4().hex}"
        atexit.register(_remove, spark, _made[app])
    return f"{_made[app]}/{tag}-{uuid.uuid4().hex[:12]}"


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        place = jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
    except Exception:  # the JVM may be gone already
        return


def drop(df_path: str, spark: SparkSession) -> None:
    """Delete a folder made by :func:`new_folder` before the application ends."""
    _remove(spark, df_path)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back.

    The written table replaces lineage: a lost executor costs a re-read of its
    Parquet parts, not a recomputation of Python stages. Shuffle files of the
    writing go when it is done.
    """
    spark = df.sparkSession
    path = new_folder(spark, tag)
    before = spark.conf.get(CLEAN_UP)
    spark.conf.set(CLEAN_UP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEAN_UP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path
    return out


def discard(df: DataFrame) -> None:
    """Delete what :func:`materialise` wrote for ``df``, which nothing reads any more."""
    drop(df._written_at, df.sparkSession)


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once for each application, and keep Arrow batches small."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    top = Path(__file__).resolve().parents[1]
    out = os.path.join(tempfile.mkdtemp(prefix="lexnorm-"), "lexnorm_package.zip")
    with zipfile.ZipFile(out, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, str(Path(top.name) / p.relative_to(top)))
    spark.sparkContext.addPyFile(out)
    _shipped.add(app)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
