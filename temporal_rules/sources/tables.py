"""Reading tables of several formats as facts, and writing facts in a layout that prunes by time."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import DAYS, HI, LO, NEG, POS, TemporalRelation, Timeline, points, relation
from ..operators.joins import hold_until_next

__all__ = ["load_table", "facts_from", "from_points", "from_ranges", "hold_until_next", "write_facts", "read_facts", "load_rules"]


def load_table(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """parquet, orc, json, csv or a catalog table (fmt 'table'); text formats want a schema, so that no pass infers it."""
    if fmt == "table":
        return spark.table(path)
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} files need a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def facts_from(df: DataFrame, keys, start: str, end: str | None = None, closed: str = "[)", timeline: Timeline = DAYS) -> TemporalRelation:
    """Validity columns as intervals; ``closed`` names both brackets; no end column means instants."""
    if end is None:
        return points(df, keys, start, timeline)
    return relation(df, keys, start, end, timeline, closed[0] == "(", closed[1] == ")")


from_points = points
from_ranges = relation


def load_rules(spark: SparkSession, path: str) -> str:
    """Rule text from a file that only Spark may be able to reach."""
    return "\n".join(r.value for r in spark.read.text(path).collect())


def write_facts(r: TemporalRelation, path: str, bucket: int = 730, name: str = "fact", mode: str = "overwrite") -> None:
    """Parquet by coarse start bucket, sorted by key and start inside files; facts longer than two buckets and
    endless ones have a bucket of their own, so a query over a span reads few others."""
    long = (F.col(HI) >= POS) | (F.col(LO) <= NEG) | (F.col(HI) - F.col(LO) > 2 * bucket)
    df = r.df.withColumn("predicate", F.lit(name)).withColumn("start_bucket", F.when(long, F.lit("long")).otherwise(F.expr(f"string({LO} div {bucket})")))
    df.repartition("start_bucket").sortWithinPartitions("start_bucket", *r.keys, LO).write.mode(mode).partitionBy("predicate", "start_bucket").parquet(path)


def read_facts(spark: SparkSession, path: str, keys, timeline: Timeline = DAYS, name: str = "fact", span: tuple[int, int] | None = None, bucket: int = 730) -> TemporalRelation:
    """Facts that meet cells ``span``: buckets are pruned by name, rows by the files' minima and maxima."""
    df = spark.read.parquet(path).where(F.col("predicate") == name)
    if span:
        a, b = span
        near = [str(int(x)) for x in range(int(a / bucket) - 3, int(b / bucket) + 1)]
        df = df.where(F.col("start_bucket").cast("string").isin("long", *near)).where((F.col(LO) <= b) & (F.col(HI) >= a))
    return TemporalRelation(df.select(*keys, LO, HI), tuple(keys), timeline)
