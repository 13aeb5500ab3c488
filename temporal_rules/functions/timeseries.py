"""Time-series operators over regular series on discrete time.

A series is a DataFrame with key columns, an integer time ``t`` and a value ``v``; every
operator returns such a frame.  Windows are by time, not by row, so missing points stay
missing.  Values of one window are a bag: equal ones count separately (``set_semantics`` gives
the reading in which facts with equal values are one).
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import STEPS, Range, TemporalRelation, points
from ..staging import staged


@dataclass(frozen=True)
class Series:
    df: DataFrame
    keys: tuple[str, ...]
    t: str = "t"
    v: str = "v"

    @classmethod
    def of(cls, df: DataFrame, keys, t, v) -> "Series":
        t = F.col(t) if isinstance(t, str) else t
        v = F.col(v) if isinstance(v, str) else v
        return cls(df.select(*keys, t.cast("long").alias("t"), v.cast("double").alias("v")), tuple(keys))

    def with_df(self, df: DataFrame) -> "Series":
        return replace(self, df=df)

    @property
    def by_time(self):
        return Window.partitionBy(*self.keys).orderBy("t")

    def facts(self) -> TemporalRelation:
        """The series as punctual facts."""
        return points(self.df, (*self.keys, "v"), "t", STEPS)


def shift(s: Series, k: int) -> Series:
    return s.with_df(s.df.select(*s.keys, (F.col("t") + k).alias("t"), "v"))


def _window(s: Series, before: int, after: int):
    return s.by_time.rangeBetween(-before, after)


def rolling(s: Series, n: int, f: str = "sum", partial: bool = False, set_semantics: bool = False) -> Series:
    """An aggregate over the last n ticks at every point; full windows only unless ``partial``."""
    w = _window(s, n - 1, 0)
    values = F.collect_set("v").over(w) if set_semantics else None
    if set_semantics:
        total = F.aggregate(values, F.lit(0.0), lambda a, x: a + x)
        got = {"sum": total, "avg": total / F.size(values), "count": F.size(values).cast("double"), "min": F.array_min(values), "max": F.array_max(values)}[f]
    else:
        got = {"sum": F.sum, "avg": F.avg, "min": F.min, "max": F.max, "count": F.count}[f]("v").over(w).cast("double")
    df = s.df.select(*s.keys, "t", got.alias("v"), F.count(F.lit(1)).over(w).alias("__n"))
    return s.with_df((df if partial else df.where(F.col("__n") == n)).select(*s.keys, "t", "v"))


def rolling_by_rules(s: Series, n: int) -> TemporalRelation:
    """The two-rule form: every point holds for n ticks and is joined with the series again; ``source`` keeps
    equal values apart."""
    from ..operators.joins import temporal_join
    from ..operators.unary import sometime_past

    base = points(s.df.withColumn("source", F.col("t")), (*s.keys, "source", "v"), "t", STEPS)
    wide = sometime_past(base, Range(0, n, False, True))
    at = points(s.df, s.keys, "t", STEPS)
    return temporal_join(at, wide, list(s.keys))


def sma(s: Series, n: int, partial: bool = False) -> Series:
    return rolling(s, n, "avg", partial)


def cma(s: Series, n: int, even: str = "two_by_n") -> Series:
    """The moving average at the middle of its window.  An even n has no middle: the mean of the two n-windows
    around the point (ends weigh half)."""
    h = n // 2
    if n % 2:
        return shift(sma(s, n), -h)
    if even != "two_by_n":
        raise ValueError("even windows are averaged two by n")
    w1, w2 = _window(s, h, h - 1), _window(s, h - 1, h)
    df = s.df.select(*s.keys, "t", ((F.avg("v").over(w1) + F.avg("v").over(w2)) / 2).alias("v"), F.count(F.lit(1)).over(w1).alias("a"), F.count(F.lit(1)).over(w2).alias("b"))
    return s.with_df(df.where((F.col("a") == n) & (F.col("b") == n)).select(*s.keys, "t", "v"))


def downsample(s: Series, unit: Column, f: str = "avg") -> Series:
    """One value for each coarser unit, an expression of t."""
    got = {"avg": F.avg, "sum": F.sum, "min": F.min, "max": F.max, "count": F.count}[f]("v").cast("double")
    return s.with_df(s.df.groupBy(*s.keys, unit.cast("long").alias("t")).agg(got.alias("v")).select(*s.keys, "t", "v"))


def upsample(s: Series, step: int = 1, method: str = "linear") -> Series:
    """Points every ``step`` ticks between neighbouring ones: on the line between them, or the last value."""
    nt, nv = F.lead("t").over(s.by_time), F.lead("v").over(s.by_time)
    df = s.df.select(*s.keys, "t", "v", nt.alias("nt"), nv.alias("nv"))
    df = df.withColumn("z", F.explode(F.sequence("t", F.coalesce(F.col("nt") - 1, F.col("t")), F.lit(step).cast("long"))))
    line = F.col("v") + (F.col("nv") - F.col("v")) * (F.col("z") - F.col("t")) / (F.col("nt") - F.col("t"))
    v = F.when(F.col("z") == F.col("t"), F.col("v")).otherwise(line if method == "linear" else F.col("v"))
    return s.with_df(df.select(*s.keys, F.col("z").alias("t"), v.alias("v")))


def ema(s: Series, n: int, seed: str = "sma") -> Series:
    """Exponential average with k = 2 / (n + 1) over the points in order, from the mean of the first n (seed
    'sma', at the n-th point) or from the first ('first').

    One ordered fold for each series, in a state of one number while its rows stream by.
    """
    k = 2.0 / (1 + n)
    keys = list(s.keys)

    def fold(batches):
        last, count, total, y = None, 0, 0.0, 0.0
        for batch in batches:
            cols = [batch.column(c).to_pylist() for c in keys]
            names = list(zip(*cols)) if cols else [()] * batch.num_rows
            out, keep = [], []
            for i, (name, v) in enumerate(zip(names, batch.column("v").to_pylist())):
                if name != last or i == 0 and last is None:
                    last, count, total, y = name, 0, 0.0, 0.0
                count += 1
                if seed == "sma" and count <= n:
                    total += v
                    if count < n:
                        continue
                    y = total / n
                elif count == 1:
                    y = v
                else:
                    y = k * v + (1 - k) * y
                out.append(y)
                keep.append(i)
            yield pa.record_batch([*(batch.column(c).take(pa.array(keep, pa.int64())) for c in keys), batch.column("t").take(pa.array(keep, pa.int64())), pa.array(out, pa.float64())], [*keys, "t", "v"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in s.df.select(*keys).schema), "t long, v double"])
    dealt = s.df.where("v is not null").select(*keys, "t", "v")
    dealt = dealt.repartition(*keys) if keys else dealt.coalesce(1)
    return s.with_df(dealt.sortWithinPartitions(*keys, "t").mapInArrow(fold, schema))


def _before_blocks(s: Series, width: int, value: Column, out: str) -> DataFrame:
    """The series with a running total of ``value`` up to and with each row, over blocks of ``width`` ticks: block
    totals are summed per series, rows only within their block, so one long series is many small windows."""
    keys = [*s.keys, "__block"]
    df = s.df.where("v is not null").select(*s.keys, "t", "v", F.floor(F.col("t") / width).alias("__block"), value.alias("__value"))
    totals = df.groupBy(*keys).agg(F.sum("__value").alias("__total"))
    w = Window.partitionBy(*s.keys).orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    before = totals.select(*keys, F.coalesce(F.sum("__total").over(w), F.lit(0)).alias("__before"))
    inner = Window.partitionBy(*keys).orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return df.join(before, keys).select(*s.keys, "t", "v", (F.col("__before") + F.sum("__value").over(inner)).alias(out))


def ema_blocks(s: Series, n: int, block: int = 4096) -> Series:
    """The same average for very long series: blocks of points fold to y -> a y + b, blocks are chained in
    order, and every point is its block's start value and a running weighted sum.  Only block rows meet."""
    k = 2.0 / (1 + n)
    if k >= 1:
        return s.with_df(s.df.where("v is not null").select(*s.keys, "t", "v"))
    # Weights within a block stay inside the range of doubles.
    block = max(1, min(block, int(200 / -math.log(1 - k))))
    keys = list(s.keys)
    ranked = staged(_before_blocks(s, 4 * block, F.lit(1).cast("long"), "i"), "series")
    seeds = ranked.where(F.col("i") <= n).groupBy(*keys).agg(F.avg("v").alias("v"), F.count(F.lit(1)).alias("c"), F.max("t").alias("t")).where(F.col("c") == n)
    rest = ranked.where(F.col("i") > n).withColumn("block", F.floor((F.col("i") - n - 1) / block)).withColumn("r", F.col("i") - n - F.col("block") * block)
    rest = rest.withColumn("w", k * F.col("v") * F.pow(F.lit(1 - k), -F.col("r").cast("double")))
    sums = rest.groupBy(*keys, "block").agg(F.sum("w").alias("w"), F.max("r").alias("m"))
    steps = seeds.select(*keys, F.lit(-1).cast("long").alias("block"), "v", F.lit(0).cast("long").alias("m")).unionByName(sums.select(*keys, "block", F.col("w").alias("v"), F.col("m").cast("long").alias("m")))

    def chain(batches):
        last, y, known = None, 0.0, False
        for batch in batches:
            names = list(zip(*(batch.column(c).to_pylist() for c in keys))) if keys else [()] * batch.num_rows
            out = []
            for name, at, v, m in zip(names, batch.column("block").to_pylist(), batch.column("v").to_pylist(), batch.column("m").to_pylist()):
                if at < 0:
                    last, y = name, v
                    out.append(v)
                elif name == last:
                    out.append(y)
                    y = (1 - k) ** m * (y + v)
                else:
                    out.append(None)
            yield pa.record_batch([*(batch.column(c) for c in keys), batch.column("block"), pa.array(out, pa.float64())], [*keys, "block", "y0"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in s.df.select(*keys).schema), "block long, y0 double"])
    dealt = steps.repartition(*keys) if keys else steps.coalesce(1)
    starts = dealt.sortWithinPartitions(*keys, "block").mapInArrow(chain, schema)
    run = F.sum("w").over(Window.partitionBy(*keys, "block").orderBy("r").rowsBetween(Window.unboundedPreceding, 0))
    parts = rest.withColumn("run", run).join(starts.where("block >= 0"), [*keys, "block"]).select(*keys, "t", (F.pow(F.lit(1 - k), F.col("r").cast("double")) * (F.col("y0") + F.col("run"))).alias("v"))
    return s.with_df(seeds.select(*keys, "t", "v").unionByName(parts))


def stock_to_flow(s: Series) -> Series:
    """Change against the tick before; none after a gap."""
    w = s.by_time
    df = s.df.select(*s.keys, "t", (F.col("v") - F.lag("v").over(w)).alias("v"), F.lag("t").over(w).alias("p"))
    return s.with_df(df.where(F.col("p") == F.col("t") - 1).select(*s.keys, "t", "v"))


def flow_to_stock(s: Series, block: int | None = None) -> Series:
    """Cumulative sums from the start; ``block`` ticks at a time for very long series."""
    if block:
        return s.with_df(_before_blocks(s, block, F.col("v"), "total").select(*s.keys, "t", F.col("total").alias("v")))
    return s.with_df(s.df.select(*s.keys, "t", F.sum("v").over(s.by_time.rowsBetween(Window.unboundedPreceding, 0)).alias("v")))


def add(s: Series, r: Series, sign: int = 1) -> Series:
    j = s.df.alias("a").join(r.df.select(*r.keys, "t", F.col("v").alias("w")), [*s.keys, "t"])
    return s.with_df(j.select(*s.keys, "t", (F.col("v") + sign * F.col("w")).alias("v")))


@dataclass(frozen=True)
class Decomposition:
    """Additive: series = trend + seasonal + residual where the trend exists."""

    trend: Series
    detrend: Series
    seasonal: Series
    residual: Series


def decompose(s: Series, period: int, divisor: str = "observed", periods: int | None = None) -> Decomposition:
    """Trend by centred average; the mean of what is left for each phase; the rest.  ``divisor`` 'periods'
    divides by a stated number of periods instead of the points observed."""
    trend = cma(s, period)
    detrend = add(s, trend, -1)
    phase = F.pmod(F.col("t"), F.lit(period))
    w = Window.partitionBy(*s.keys, phase)
    mean = F.avg("v").over(w) if divisor == "observed" else F.sum("v").over(w) / periods
    seasonal = s.with_df(detrend.df.select(*s.keys, "t", mean.alias("v")))
    residual = s.with_df(detrend.df.select(*s.keys, "t", (F.col("v") - mean).alias("v")))
    return Decomposition(trend, detrend, seasonal, residual)


def frequency(s: Series) -> DataFrame:
    """For every series its least and greatest spacing and whether it is regular."""
    d = s.df.select(*s.keys, (F.col("t") - F.lag("t").over(s.by_time)).alias("d"))
    return d.groupBy(*s.keys).agg(F.min("d").alias("least"), F.max("d").alias("most"), F.coalesce(F.min("d") == F.max("d"), F.lit(True)).alias("regular"))
