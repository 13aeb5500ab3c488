"""What the corpus operators share: the folder that all machines see, staged tables, numbered hash buckets."""

from __future__ import annotations

import ctypes
import gc
import os
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..staging import shared_folder

PACKAGE_HOME = str(Path(__file__).resolve().parents[2])


def session_of(df: DataFrame) -> SparkSession:
    return df.sparkSession


def reach_workers(spark: SparkSession, rows: int = 1_000, size: int = 6 << 20) -> None:
    """Let Python workers import this package when the driver found it by its own path only, and hand them
    Arrow batches of bounded size: texts are long, and a batch is held by the JVM and by the worker."""
    for name, most in (("maxRecordsPerBatch", rows), ("maxBytesPerBatch", size)):
        spark.conf.set(f"spark.sql.execution.arrow.{name}", str(most))
    env = spark.sparkContext.environment
    known = env.get("PYTHONPATH", "")
    if PACKAGE_HOME not in known.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (known, PACKAGE_HOME) if x)


_kept: dict = {}


def kept(key, make):
    """A large model that a worker keeps from task to task: one at a time."""
    if key not in _kept:
        _kept.clear()
        _kept[key] = make()
    return _kept[key]


def let_go() -> None:
    """Free it; called first by tasks that hold other large things, which the same workers run.

    Freed memory goes back to the machine at once: later objects would keep its pages in use.
    """
    if not _kept:
        return
    _kept.clear()
    gc.collect()
    give_back()


def give_back() -> None:
    """Hand the allocator's free pages back to the machine, where the C library can."""
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/llm-{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write a frame to the shared folder and read it back: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def forget(df: DataFrame) -> None:
    """Delete a staged table that nothing will read again."""
    path = getattr(df, "_staged_at", None)
    if path:
        jvm = df.sparkSession.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


SMALL = 300_000  # rows of ids or bucket heads that may be broadcast; beyond it the join shuffles


def maybe_broadcast(df: DataFrame, limit: int = SMALL) -> DataFrame:
    return F.broadcast(df) if df.count() <= limit else df


def words_of(text: str = "text"):
    """Number of words [^\\x20\\x09-\\x0D]+ of a text column; null counts 0."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long")


def numbered(df: DataFrame, group: list[str], salt: str, order: list[str], weight: str | None, out: str, rows_per_bucket: int = 50_000) -> DataFrame:
    """Running total before each row (of ``weight``, or of rows) within ``group``, in the order of (salt, order).

    ``salt`` is a hash column of uniform 64-bit values.  Its leading bits deal every group over
    buckets, so a group that holds a third of all rows is still many small windows; the
    bucket totals are aggregated before the shuffle and only they are summed per group.
    The frame is read twice; stage it first.
    """
    n = df.count()
    bits = max(0, (max(1, n) // rows_per_bucket).bit_length())
    bucket = F.lit(0).cast("long") if not bits else F.shiftrightunsigned(F.col(salt), 64 - bits)
    value = F.lit(1).cast("long") if weight is None else F.col(weight)
    df = df.withColumn("__bucket", bucket)
    by = ",".join([f"`{c}`" for c in group])
    totals = df.groupBy(*group, "__bucket").agg(F.sum(value).alias("__total"))
    # One row for each group and bucket: bounded by groups x n / rows_per_bucket.
    before = totals.withColumn("__before", F.expr(f"coalesce(sum(__total) over (partition by {by or '1'} order by __bucket rows between unbounded preceding and 1 preceding), 0)"))
    keys = [*group, "__bucket"]
    on = None
    left, right = df.alias("l"), before.drop("__total").alias("r")
    for k in keys:
        c = F.col(f"l.{k}").eqNullSafe(F.col(f"r.{k}"))
        on = c if on is None else on & c
    joined = left.join(right, on).select("l.*", "r.__before")
    part = ",".join(f"`{k}`" for k in keys)
    sort = ",".join(f"`{c}`" for c in [salt, *order])
    inner = "1" if weight is None else f"`{weight}`"
    run = F.expr(f"coalesce(sum({inner}) over (partition by {part} order by {sort} rows between unbounded preceding and 1 preceding), 0)")
    return joined.withColumn(out, (F.col("__before") + run).cast("long")).drop("__before", "__bucket")
