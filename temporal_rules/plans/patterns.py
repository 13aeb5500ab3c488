"""Infinite models as finite tables: facts that repeat for ever, and facts that never end."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce
from math import gcd

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import HI, LO, NEG, POS, Range, TemporalRelation
from ..operators.joins import temporal_join, temporal_minus
from ..operators.merge import coalesce


class NeedsWindow(Exception):
    """A rule over facts that repeat for ever whose answer needs a stretch of their occurrences written out."""


@dataclass(frozen=True)
class PatternRelation:
    """Occurrence x >= n0 of a row holds over [__lo + x period, __hi + x period] (period in cells).

    ``steps`` are columns whose value moves as well: v -> a v + b from one occurrence to the next.
    """

    base: TemporalRelation
    period: int
    n0: int = 0
    steps: tuple[tuple[str, tuple[float, float]], ...] = ()

    def column(self, name: str, at: Column, source: str | None = None) -> Column:
        """A column's value in occurrence ``at``."""
        c, kind = F.col(source or name), self.base.df.schema[name].dataType
        if name not in dict(self.steps):
            return c
        a, b = dict(self.steps)[name]
        if a == 1:
            return (c + at * F.lit(int(b) if b == int(b) else b)).cast(kind)
        power = F.pow(F.lit(float(a)), at.cast("double"))
        return (c * power + F.lit(float(b)) * (power - 1) / F.lit(float(a - 1))).cast(kind)

    def unroll(self, start: int, end: int) -> TemporalRelation:
        """All occurrences that meet cells [start, end], whole."""
        p = self.period
        first = F.greatest(F.lit(self.n0), F.ceil((F.lit(start) - F.col(HI)) / p).cast("long"))
        last = F.floor((F.lit(end) - F.col(LO)) / p).cast("long")
        x = self.base.df.withColumn("__x", F.explode(F.when(first <= last, F.sequence(first, last))))
        at = F.col("__x")
        moved = x.select(*(self.column(k, at).alias(k) for k in self.base.keys), (F.col(LO) + at * p).alias(LO), (F.col(HI) + at * p).alias(HI))
        return self.base.with_df(moved)

    def stretched(self, period: int) -> "PatternRelation":
        """The same facts over a multiple of the period."""
        times = period // self.period
        if times == 1 and not self.n0:
            return self
        if self.steps:
            raise NeedsWindow
        x = self.base.df.withColumn("__x", F.explode(F.sequence(F.lit(self.n0), F.lit(self.n0 + times - 1))))
        by = F.col("__x") * self.period
        return PatternRelation(self.base.with_df(x.select(*self.base.keys, (F.col(LO) + by).alias(LO), (F.col(HI) + by).alias(HI))), period)


def with_repeats(r: TemporalRelation, p: PatternRelation | None) -> TemporalRelation:
    return replace(r, repeats=p)


def only_pattern(p: PatternRelation) -> TemporalRelation:
    """A relation without rows of its own that repeats."""
    return with_repeats(p.base.with_df(p.base.df.limit(0), coalesced=True), p)


def common_period(periods, most: int = 100_000) -> int:
    out = 1
    for p in periods:
        out = out * p // gcd(out, p)
    if any(out // p > most for p in periods):
        raise ValueError(f"the joint pattern repeats only after {out} cells")
    return out


def merged_patterns(patterns: list[PatternRelation]) -> PatternRelation | None:
    """Several patterns of one predicate as one, over their common period."""
    if len(patterns) < 2:
        return patterns[0] if patterns else None
    period = common_period([p.period for p in patterns])
    parts = [p.stretched(period) for p in patterns]
    keys = parts[0].base.keys
    return PatternRelation(parts[0].base.with_df(reduce(lambda a, b: a.unionByName(b), [p.base.df.select(*keys, LO, HI) for p in parts])), period)


def pattern_join(p: PatternRelation, r: TemporalRelation, on: list[str], buckets: int = 256) -> TemporalRelation:
    """Every fact of r that ends with the occurrences that it meets; only their numbers are generated.

    Without join keys both sides are dealt over buckets of the time within a period, and a meeting is reported
    in the bucket where it starts, so the join is by equality whatever the sizes.  Endless facts of r meet
    endlessly many occurrences and are left out (see ``joined``).
    """
    step, moving = p.period, dict(p.steps)
    plain = [k for k in on if k not in moving]
    left = r.df.where(F.col(HI) < POS)
    right = p.base.df
    if not plain:
        width = max(1, -(-step // buckets))
        n = -(-step // width)

        def dealt(df: DataFrame) -> DataFrame:
            lo = F.greatest(F.col(LO), F.lit(NEG // 2))  # an endless past meets an occurrence in every bucket
            a = F.floor(F.pmod(lo, F.lit(step)) / width)
            covered = F.least(F.lit(n - 1), F.floor((F.pmod(lo, F.lit(step)) + F.col(HI) - lo) / width) - a + 1)
            return df.withColumn("__b", F.explode(F.transform(F.sequence(a, a + covered), lambda x: F.pmod(x, F.lit(n)))))

        left, right = dealt(left), dealt(right)
    keyed = [F.col(f"r.{k}") == F.col(f"p.{k}") for k in plain] or [F.col("r.__b") == F.col("p.__b")]
    pairs = left.alias("r").join(right.alias("p"), reduce(lambda a, b: a & b, keyed))
    first = F.greatest(F.lit(p.n0), F.ceil((F.col(f"r.{LO}") - F.col(f"p.{HI}")) / step).cast("long"))
    last = F.floor((F.col(f"r.{HI}") - F.col(f"p.{LO}")) / step).cast("long")
    x = pairs.withColumn("__x", F.explode(F.when(first <= last, F.sequence(first, last))))
    at = F.col("__x")
    lo, hi = F.greatest(F.col(f"r.{LO}"), F.col(f"p.{LO}") + at * step), F.least(F.col(f"r.{HI}"), F.col(f"p.{HI}") + at * step)
    if not plain:
        x = x.where(F.floor(F.pmod(lo, F.lit(step)) / width) == F.col("r.__b"))
    for k in on:
        if k in moving:
            x = x.where(F.col(f"r.{k}") == p.column(k, at, f"p.{k}"))
    keys = [*r.keys, *(k for k in p.base.keys if k not in r.keys)]
    cols = [F.col(f"r.{k}").alias(k) for k in r.keys] + [p.column(k, at, f"p.{k}").alias(k) for k in p.base.keys if k not in r.keys]
    return r.with_df(x.select(*cols, lo.alias(LO), hi.alias(HI)).where(F.col(LO) <= F.col(HI)), keys)


def pattern_minus(r: TemporalRelation, p: PatternRelation, on: list[str]) -> TemporalRelation:
    """r without the occurrences of p; those that its facts meet are all that is generated."""
    if not r.df.where(F.col(HI) >= POS).isEmpty():
        raise NeedsWindow
    near = coalesce(r.select(**{k: k for k in on})) if on else coalesce(r.with_df(r.df.select(LO, HI), ()))
    base = replace(p, base=p.base.select(**{k: k for k in on}) if on else p.base.with_df(p.base.df.select(LO, HI), ()))
    return temporal_minus(r, pattern_join(base, near, on), on)


def joined(r: TemporalRelation, s: TemporalRelation, on: list[str]) -> TemporalRelation:
    """A temporal join where one side may have a pattern besides its rows."""
    if r.repeats is not None and s.repeats is None:
        r, s = s, r
    if s.repeats is None:
        return temporal_join(r, s, on)
    if r.repeats is not None or not r.df.where(F.col(HI) >= POS).isEmpty():
        raise NeedsWindow
    met = pattern_join(s.repeats, r, on)
    own = temporal_join(r, with_repeats(s, None), on)
    return own.with_df(own.df.select(*met.keys, LO, HI).unionByName(met.df), met.keys)


def pattern_pattern_join(p: PatternRelation, q: PatternRelation, on: list[str], most: int = 100_000) -> PatternRelation:
    """Where both hold, from when every row of both has begun; the result repeats after the least common multiple."""
    lcm = common_period([p.period, q.period], most)
    ends = [x.base.df.agg(F.min(LO).alias("a"), F.max(LO).alias("z"), F.max(HI).alias("b")).first() for x in (p, q)]
    if any(e["a"] is None for e in ends):
        return PatternRelation(p.base.with_df(p.base.df.limit(0)), lcm)
    begin = max(e["z"] + x.n0 * x.period for e, x in zip(ends, (p, q)))
    width = max(e["b"] - e["a"] for e in ends)
    met = temporal_join(p.unroll(begin - width, begin + lcm + width), q.unroll(begin - width, begin + lcm + width), on)
    return PatternRelation(met.with_df(met.df.where((F.col(LO) >= begin) & (F.col(LO) < begin + lcm))), lcm)


def accelerate_constant(r: TemporalRelation, rng: Range) -> TemporalRelation:
    """The least model of ``p :- past[rng] p`` over r, for a range of more than one instant.

    Copy k of a fact is moved by [k t1, k t2].  From the first k whose copies touch, all time is
    covered: so many prefix rows and one endless row for each fact, then a coalesce.
    """
    rng = rng.on(r.timeline)
    if rng.hi is None:
        from ..operators.unary import sometime_past

        return coalesce(r.with_df(r.df.select(*r.keys, LO, HI).unionByName(sometime_past(r, rng).df)))
    if rng.lo == rng.hi:
        raise ValueError("a range of one instant repeats for ever; use a pattern")
    s = r.timeline.scale
    a, b = s * rng.lo, s * rng.hi
    # An open end of the range opens a copy's end once, however often the fact is moved.
    k0 = F.greatest(F.lit(0), F.ceil((F.col(LO) - F.col(HI) + F.lit(a + int(rng.lo_open) + int(rng.hi_open) - 1)) / (b - a)).cast("long"))
    df = r.df.withColumn("__k", F.explode(F.sequence(F.lit(0).cast("long"), k0)))
    k, moved = F.col("__k"), F.col("__k") > 0
    lo, hi = F.col(LO) + k * a, F.col(HI) + k * b
    lo = F.when(moved, lo.bitwiseOR(F.lit(1))).otherwise(lo) if rng.lo_open else lo
    hi = F.when(moved, (hi - 1).bitwiseOR(F.lit(1))).otherwise(hi) if rng.hi_open else hi
    out = df.select(*r.keys, lo.alias(LO), F.when(k == k0, F.lit(POS)).otherwise(hi).alias(HI)).where(F.col(LO) <= F.col(HI))
    return coalesce(r.with_df(out))


def admit(delta: TemporalRelation, known: PatternRelation) -> TemporalRelation:
    """The part of new facts that a pattern does not already say; only its occurrences near them are generated."""
    return pattern_minus(delta, known, list(delta.keys))


def recognise(rows: DataFrame, keys, period: int) -> DataFrame:
    """Base rows of a fixpoint whose facts repeat after ``period``: the first fact of every residue."""
    return rows.groupBy(*keys, F.pmod(F.col(LO), F.lit(period)).alias("__r"), (F.col(HI) - F.col(LO)).alias("__w")).agg(F.min(LO).alias(LO)).select(*keys, LO, (F.col(LO) + F.col("__w")).alias(HI))
