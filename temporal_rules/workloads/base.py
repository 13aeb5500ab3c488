"""Base relations of the workloads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.timeseries import Series
from ..model import MICROS, STEPS, TemporalRelation, Timeline, points, relation
from ..operators.joins import hold_until_next

EPOCH = "1995-01-01"
HOUR = 3_600_000_000
HOURS = Timeline(True, "hour")
BIG, LINKED = 94_700, 53_000


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def day(c: str) -> Column:
    return F.datediff(F.col(c).cast("date"), F.lit(EPOCH).cast("date")).cast("long")


def stake(spark, sf, over: float = 0) -> TemporalRelation:
    """(cust, supp, price) during [order day, + quantity days)."""
    o = table(spark, sf, "orders").select("o_orderkey", F.col("o_custkey").alias("cust"), day("o_orderdate").alias("s"))
    l = table(spark, sf, "lineitem").select("l_orderkey", F.col("l_suppkey").alias("supp"), F.col("l_extendedprice").alias("price"), F.col("l_quantity").cast("long").alias("q"))
    if over:
        l = l.where(F.col("price") > over)
    df = l.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return relation(df, ["cust", "supp", "price"], F.col("s"), F.col("s") + F.col("q"))


def pairs(spark, sf, over: float) -> TemporalRelation:
    return stake(spark, sf, over).select(cust="cust", supp="supp")


def big(spark, sf) -> TemporalRelation:
    return pairs(spark, sf, BIG)


def linked(spark, sf) -> TemporalRelation:
    return pairs(spark, sf, LINKED)


def big_by_supp(spark, sf) -> TemporalRelation:
    return big(spark, sf).select(supp="supp")


def seed(spark, sf) -> TemporalRelation:
    s = table(spark, sf, "supplier").where("s_suppkey % 20 = 0").select(F.col("s_suppkey").alias("supp"), F.lit(0).alias("s"), F.lit(2500).alias("e"))
    return relation(s, ["supp"], "s", "e")


def exempt(spark, sf) -> TemporalRelation:
    s = table(spark, sf, "supplier").where("s_acctbal < 0").select(F.col("s_suppkey").alias("supp"), F.lit(500).alias("s"), F.lit(1500).alias("e"))
    return relation(s, ["supp"], "s", "e")


def placed(spark, sf) -> TemporalRelation:
    o = table(spark, sf, "orders").select(F.col("o_custkey").alias("cust"), F.col("o_orderkey").alias("ord"), day("o_orderdate").alias("d"))
    return points(o, ["cust", "ord"], "d")


def reading(spark, sf) -> TemporalRelation:
    e = table(spark, sf, "events").select("user_id", F.expr("unix_micros(cast(ts as timestamp))").alias("at"), "value")
    return hold_until_next(e, ["user_id"], "at", MICROS, ["value"])


def hourly(spark, sf) -> DataFrame:
    e = table(spark, sf, "events")
    return e.select("user_id", "event_type", "value", F.expr("(unix_micros(cast(ts as timestamp)) - 1704067200000000) div 3600000000").alias("h"))


def said(spark, sf, role: str) -> TemporalRelation:
    c = table(spark, sf, "conversations").where(F.col("role") == role)
    return points(c, ["conv_id"], "turn", STEPS)


def daily_revenue(spark, sf) -> Series:
    l = table(spark, sf, "lineitem")
    value = F.sum(F.col("l_extendedprice").cast("decimal(12,2)") * (1 - F.col("l_discount").cast("decimal(4,2)")))
    df = l.groupBy("l_returnflag", "l_linestatus", day("l_shipdate").alias("t")).agg(value.cast("double").alias("v"))
    return Series(df.select("l_returnflag", "l_linestatus", "t", "v"), ("l_returnflag", "l_linestatus"))


def daily_orders(spark, sf) -> Series:
    df = table(spark, sf, "orders").groupBy(F.col("o_orderpriority").alias("priority"), day("o_orderdate").alias("t")).agg(F.count(F.lit(1)).cast("double").alias("v"))
    return Series(df.select("priority", "t", "v"), ("priority",))


def vector_series(spark, sf) -> Series:
    df = table(spark, sf, "embeddings").select("vec_id", F.posexplode("embedding").alias("t", "v"))
    return Series.of(df, ["vec_id"], "t", "v")


def daily_events(spark, sf) -> Series:
    """Sums of events by type and day; a day without events has value 0 only where it has rows."""
    e = table(spark, sf, "events")
    t = F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).cast("long")
    df = e.groupBy("event_type", t.alias("t")).agg(F.sum(F.col("value").cast("decimal(18,4)")).cast("double").alias("v"))
    return Series(df.select("event_type", "t", "v"), ("event_type",))


def generate_facts(spark, n: int, domain: int, horizon: int, seed_: int, length: int = 20) -> TemporalRelation:
    """n seeded facts of random keys and intervals; the same rows on any cluster."""
    h = lambda salt: F.pmod(F.xxhash64("id", F.lit(seed_), F.lit(salt)), F.lit(1 << 40))
    df = spark.range(n).select((h(1) % domain).alias("k"), (h(2) % horizon).alias("s"), (h(3) % length + 1).alias("len"))
    return relation(df, ["k"], F.col("s"), F.col("s") + F.col("len"))
