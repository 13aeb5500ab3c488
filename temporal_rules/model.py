"""Intervals as two integers, timelines, operator ranges and temporal relations.

On a dense timeline the point k is cell 2k and the open gap between k and k+1 is cell 2k+1, so
every interval with whole ends, open or closed, is one closed range of cells and truth is
constant in a cell.  On a discrete timeline a cell is a tick.  Infinite ends are sentinels.
All interval arithmetic is then integer expressions that Catalyst compiles.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LO, HI = "__lo", "__hi"
POS, NEG = 1 << 61, -(1 << 61)


@dataclass(frozen=True)
class Timeline:
    """``dense`` for rational time in whole ticks (gaps between ticks exist), else integers only."""

    dense: bool = True
    unit: str = "tick"

    @property
    def scale(self) -> int:
        return 2 if self.dense else 1

    def encode(self, start: Column, end: Column, start_open=False, end_open=False) -> tuple[Column, Column]:
        so = start_open if isinstance(start_open, Column) else F.lit(bool(start_open))
        eo = end_open if isinstance(end_open, Column) else F.lit(bool(end_open))
        start, end = start.cast("long"), end.cast("long")
        lo = F.coalesce(start * self.scale + F.when(so, 1).otherwise(0), F.lit(NEG))
        hi = F.coalesce(end * self.scale - F.when(eo, 1).otherwise(0), F.lit(POS))
        return lo, hi

    def decode(self, lo: Column, hi: Column) -> dict[str, Column]:
        """t_start, t_end (null: infinite) and whether each end is open."""
        finite_lo, finite_hi = lo > NEG, hi < POS
        if not self.dense:
            return {
                "t_start": F.when(finite_lo, lo), "t_end": F.when(finite_hi, hi),
                "start_open": ~finite_lo, "end_open": ~finite_hi,
            }
        odd = lambda c: F.pmod(c, F.lit(2)) == 1
        return {
            "t_start": F.when(finite_lo, F.shiftright(lo, 1)),
            "t_end": F.when(finite_hi, F.shiftright(hi + 1, 1)),
            "start_open": ~finite_lo | odd(lo), "end_open": ~finite_hi | odd(hi),
        }


DAYS = Timeline(True, "day")
MICROS = Timeline(True, "us")
STEPS = Timeline(False, "step")


@dataclass(frozen=True)
class Range:
    """The index of an operator: whole ticks from ``lo`` >= 0 to ``hi`` (None: unbounded)."""

    lo: int
    hi: int | None
    lo_open: bool = False
    hi_open: bool = False

    def __post_init__(self):
        if self.lo < 0:
            raise ValueError("operator ranges do not start before 0")
        if self.hi is not None and (self.hi < self.lo or self.hi == self.lo and (self.lo_open or self.hi_open)):
            raise ValueError("empty operator range")

    def holds(self, x: int) -> bool:
        if x < self.lo or x == self.lo and self.lo_open:
            return False
        return self.hi is None or x < self.hi or x == self.hi and not self.hi_open

    def on(self, timeline: Timeline) -> "Range":
        """On integers open ends are closed ends one further in."""
        if timeline.dense:
            return self
        hi = None if self.hi is None else self.hi - self.hi_open
        return Range(self.lo + self.lo_open, hi)

    def __str__(self):
        hi = "inf" if self.hi is None else self.hi
        return f"{'(' if self.lo_open else '['}{self.lo},{hi}{')' if self.hi_open or self.hi is None else ']'}"


@dataclass(frozen=True)
class TemporalRelation:
    """Rows of ``keys`` that hold throughout [__lo, __hi]; ``coalesced``: no two rows of a key touch.

    ``repeats`` (a pattern, see plans.patterns) are facts that hold besides the rows, again and again for ever.
    """

    df: DataFrame
    keys: tuple[str, ...]
    timeline: Timeline = DAYS
    coalesced: bool = False
    repeats: object = field(default=None, compare=False)

    def with_df(self, df: DataFrame, keys=None, coalesced: bool = False) -> "TemporalRelation":
        return replace(self, df=df, keys=tuple(self.keys if keys is None else keys), coalesced=coalesced, repeats=None)

    def select(self, **named: str | Column) -> "TemporalRelation":
        """Keys by new names; fewer keys, or computed ones, may leave rows that touch."""
        cols = [(F.col(c) if isinstance(c, str) else c).alias(n) for n, c in named.items()]
        same = {c for c in named.values() if isinstance(c, str)} >= set(self.keys)
        return self.with_df(self.df.select(*cols, LO, HI), named, self.coalesced and same)

    def where(self, condition) -> "TemporalRelation":
        return self.with_df(self.df.where(condition), coalesced=self.coalesced)

    def to_df(self, flags: bool = True) -> DataFrame:
        """Keys, t_start, t_end and, on request, which ends are open."""
        parts = self.timeline.decode(F.col(LO), F.col(HI))
        names = ["t_start", "t_end", *(["start_open", "end_open"] if flags else [])]
        return self.df.select(*self.keys, *(parts[n].alias(n) for n in names))


def relation(df: DataFrame, keys, start, end, timeline: Timeline = DAYS, start_open=False, end_open=True) -> TemporalRelation:
    """Facts from columns or expressions of start and end ticks; null ends are infinite; empty intervals go."""
    start = F.col(start) if isinstance(start, str) else start
    end = F.col(end) if isinstance(end, str) else end
    lo, hi = timeline.encode(start, end, start_open, end_open)
    out = df.select(*keys, lo.alias(LO), hi.alias(HI)).where(F.col(LO) <= F.col(HI))
    return TemporalRelation(out, tuple(keys), timeline)


def points(df: DataFrame, keys, at, timeline: Timeline = DAYS) -> TemporalRelation:
    return relation(df, keys, at, at, timeline, False, False)


def timeless(df: DataFrame, keys, timeline: Timeline = DAYS) -> TemporalRelation:
    return TemporalRelation(df.select(*keys, F.lit(NEG).alias(LO), F.lit(POS).alias(HI)), tuple(keys), timeline)


def always_true(spark, timeline: Timeline = DAYS) -> TemporalRelation:
    return timeless(spark.range(1), (), timeline).with_df(spark.range(1).select(F.lit(NEG).alias(LO), F.lit(POS).alias(HI)), (), True)


def never(spark, timeline: Timeline = DAYS) -> TemporalRelation:
    t = always_true(spark, timeline)
    return t.with_df(t.df.where(F.lit(False)), (), True)
