"""The engine for SQL users: relations as views, patterns and coalescing as table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .model import TemporalRelation
from .operators.merge import coalesce


class UnrollPattern:
    """unroll_pattern(base_lo, base_hi, period, n0, from, to): occurrences that meet [from, to]."""

    def eval(self, base_lo: int, base_hi: int, period: int, n0: int, start: int, end: int):
        x = max(n0, -((base_hi - start) // period))
        while base_lo + x * period <= end:
            yield x, base_lo + x * period, base_hi + x * period
            x += 1


def register_sql(spark: SparkSession) -> None:
    spark.udtf.register("unroll_pattern", udtf(UnrollPattern, returnType="occurrence bigint, lo bigint, hi bigint"))


def register_view(r: TemporalRelation, name: str, merged: bool = True) -> None:
    """A relation as a temporary view with keys, t_start, t_end and bracket flags."""
    (coalesce(r) if merged else r).to_df().createOrReplaceTempView(name)
