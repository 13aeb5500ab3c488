"""Since and until."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from ..model import HI, LO, Range, TemporalRelation
from .merge import coalesce
from .unary import as_transform, close, shift, shift_ends


def _reach(a: TemporalRelation, b: TemporalRelation, rng: Range, on: list[str], op: str) -> TemporalRelation:
    """((closure(a) meets b) moved by the range) cut to closure(a), for every pair of intervals."""
    rng = rng.on(b.timeline)
    keys = tuple(dict.fromkeys([*a.keys, *b.keys]))
    closed = close(coalesce(a))
    left = closed.df.select(*closed.keys, F.col(LO).alias("__alo"), F.col(HI).alias("__ahi")).alias("l")
    right = b.df.alias("r")
    meet = (F.col("__alo") <= F.col(f"r.{HI}")) & (F.col(f"r.{LO}") <= F.col("__ahi"))
    condition = reduce(lambda x, y: x & y, [F.col(f"l.{k}") == F.col(f"r.{k}") for k in on], meet)
    cols = [F.col(f"l.{k}").alias(k) for k in a.keys] + [F.col(f"r.{k}").alias(k) for k in b.keys if k not in a.keys]
    pairs = left.join(right, condition).select(*cols, "__alo", "__ahi", F.greatest("__alo", f"r.{LO}").alias(LO), F.least("__ahi", f"r.{HI}").alias(HI))
    moved = shift_ends(b.with_df(pairs, (*keys, "__alo", "__ahi")), as_transform(op, rng))
    return b.with_df(moved.df.select(*keys, F.greatest(LO, "__alo").alias(LO), F.least(HI, "__ahi").alias(HI)).where(F.col(LO) <= F.col(HI)), keys)


def _both(a: TemporalRelation, b: TemporalRelation, rng: Range, on: list[str], op: str) -> TemporalRelation:
    if set(a.keys) - set(b.keys):
        raise ValueError("every key of the left side is one of the right side")
    out = _reach(a, b, rng, on, op)
    parts = [out.df]
    sign = 1 if op == "past" else -1
    if rng.holds(0):  # no instant lies between, so the left side need not hold
        parts.append(b.df.select(*out.keys, LO, HI))
    if not b.timeline.dense and rng.holds(1):  # nor between neighbouring ticks
        parts.append(shift(b, sign).df.select(*out.keys, LO, HI))
    return coalesce(out.with_df(reduce(lambda x, y: x.unionByName(y), parts)))


def since(a: TemporalRelation, b: TemporalRelation, rng: Range, on: list[str]) -> TemporalRelation:
    """b held at some moment that far in the past, and a throughout since then."""
    return _both(a, b, rng, on, "past")


def until(a: TemporalRelation, b: TemporalRelation, rng: Range, on: list[str]) -> TemporalRelation:
    """b will hold at some moment that far in the future, and a throughout until then."""
    return _both(a, b, rng, on, "future")
