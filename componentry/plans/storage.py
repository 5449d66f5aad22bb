"""Lineage cuts and small-side checks shared by all iterative operators.

A cut writes a Parquet generation below ``spark.checkpoint.dir``, the folder that driver and
executors share, and reads it back: the plan restarts from files, so a lost executor costs a few
re-read blocks and never the rounds before.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_made: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The cluster's checkpoint folder. Where none is set, a local session (tests) gets a folder of its machine; a cluster's is refused."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        own = spark.sparkContext.getCheckpointDir()
        if own is None:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="componentry-"))
            own = spark.sparkContext.getCheckpointDir()
        found = own
    return found


def drop_path(spark: SparkSession, path: str) -> None:
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


@atexit.register
def _drop_all() -> None:
    for spark, path in _made:
        try:
            if spark.sparkContext._jsc is not None:
                drop_path(spark, path)
        except Exception:  # noqa: BLE001  the session has ended: the folder's owner clears it
            return


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Materialise ``df`` in the shared folder and return it as a scan of those files."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/componentry/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")  # a cut's plan runs once: its exchange files go with the query
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    _made.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._componentry_path = path
    return out


def release(*frames: DataFrame | None) -> None:
    """Delete the files of earlier cuts that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_componentry_path", None)
        if path:
            drop_path(df.sparkSession, path)
            _made[:] = [x for x in _made if x[1] != path]


def sweep(spark: SparkSession) -> None:
    """Collect the driver's garbage: the engine drops exchange files only once the objects of their plan are gone."""
    spark._jvm.System.gc()


BROADCAST_ROWS = 200_000


def small_side(df: DataFrame, row_bytes: int = 32, limit_bytes: int = 32 << 20) -> DataFrame:
    """``df`` with a broadcast hint if its counted rows fit ``limit_bytes``; else as it is, for a shuffle join.

    ``df`` should be a cut or a cheap scan, for it is counted here (at most one row over the limit is read).
    """
    most = min(BROADCAST_ROWS, limit_bytes // row_bytes)
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df
