"""Tables written to the folder that all machines share, to cut lineage between rounds."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_left: dict[str, SparkSession] = {}


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; a temporary folder only in local mode where it is unset."""
    known = spark.conf.get("spark.checkpoint.dir", None)
    if known:
        return known.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    got = spark.sparkContext._jsc.sc().getCheckpointDir()
    if got.isEmpty():
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="rules-shared-"))
        got = spark.sparkContext._jsc.sc().getCheckpointDir()
    return got.get().rstrip("/")


def staged(df: DataFrame, name: str = "round") -> DataFrame:
    """Write a frame and read it back.  ``forget`` deletes it; what a result still reads goes when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _left[path] = spark
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_at = [path]
    return out


def together(tables: list[DataFrame]) -> DataFrame:
    """Staged tables of one schema as one scan."""
    if len(tables) == 1:
        return tables[0]
    paths = [p for t in tables for p in t._staged_at]
    out = tables[0].sparkSession.read.schema(tables[0].schema).parquet(*paths)
    out._staged_at = paths
    return out


def forget(*tables: DataFrame) -> None:
    """Delete staged tables that nothing will read again; other frames are left alone."""
    for t in tables:
        for path in getattr(t, "_staged_at", ()):
            _delete(t.sparkSession, path)


def _delete(spark: SparkSession, path: str) -> None:
    if _left.pop(path, None) is not None:
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clean() -> None:
    for path, spark in list(_left.items()):
        if spark.sparkContext._jsc is None:
            return  # the session is stopped: its folder is the cluster's to clean
        try:
            _delete(spark, path)
        except Exception:  # the JVM may be gone already
            return
