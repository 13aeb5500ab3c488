"""Sometime and always, in the past and in the future, as arithmetic on interval ends."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..model import HI, LO, NEG, POS, Range, TemporalRelation
from .merge import coalesce


def _add(c: Column, by: int) -> Column:
    return F.when(c <= NEG, F.lit(NEG)).when(c >= POS, F.lit(POS)).otherwise(c + F.lit(by))


def _finite(c: Column, then: Column) -> Column:
    return F.when((c <= NEG) | (c >= POS), c).otherwise(then)


def _open_start(c: Column) -> Column:
    return _finite(c, c.bitwiseOR(F.lit(1)))


def _open_end(c: Column) -> Column:
    return _finite(c, (c - 1).bitwiseOR(F.lit(1)))


def _close_start(c: Column) -> Column:
    return _finite(c, c - c.bitwiseAND(F.lit(1)))


def _close_end(c: Column) -> Column:
    return _finite(c, c + c.bitwiseAND(F.lit(1)))


@dataclass(frozen=True)
class Transform:
    """Both ends moved by whole ticks.  ``widen``: an open end of the operator opens the result's end;
    otherwise (always-operators) it closes it.  None is an unbounded move.  ``merged``: its input was merged
    over the gaps that it closes, so it leaves no touching facts."""

    start: int | None
    end: int | None
    start_open: bool = False
    end_open: bool = False
    widen: bool = True
    merged: bool = False

    @property
    def grows(self) -> bool:
        return self.widen


def as_transform(op: str, rng: Range) -> Transform:
    """The four operators as moves of the ends: past adds, future subtracts; sometime widens, always shrinks."""
    a, b = rng.lo, rng.hi
    minus = None if b is None else -b
    if op == "past":
        return Transform(a, b, rng.lo_open, rng.hi_open, True)
    if op == "future":
        return Transform(minus, -a, rng.hi_open, rng.lo_open, True)
    if op == "alwayspast":
        return Transform(b, a, rng.hi_open, rng.lo_open, False)
    if op == "alwaysfuture":
        return Transform(-a, minus, rng.lo_open, rng.hi_open, False)
    raise ValueError(f"unknown operator {op}")


def shift_ends(r: TemporalRelation, t: Transform, coalesced: bool | None = None) -> TemporalRelation:
    """Apply a transform to every fact and drop what becomes empty; no exchange."""
    s = r.timeline.scale
    lo, hi = F.col(LO), F.col(HI)
    df = r.df
    if t.widen:
        new_lo = F.lit(NEG) if t.start is None else _add(lo, s * t.start)
        new_hi = F.lit(POS) if t.end is None else _add(hi, s * t.end)
        if r.timeline.dense:
            new_lo = _open_start(new_lo) if t.start_open and t.start is not None else new_lo
            new_hi = _open_end(new_hi) if t.end_open and t.end is not None else new_hi
    else:
        if t.start is None:
            df = df.where(lo <= NEG)
        if t.end is None:
            df = df.where(hi >= POS)
        new_lo = F.lit(NEG) if t.start is None else _add(lo, s * t.start)
        new_hi = F.lit(POS) if t.end is None else _add(hi, s * t.end)
        if r.timeline.dense:
            new_lo = _close_start(new_lo) if t.start_open and t.start is not None else new_lo
            new_hi = _close_end(new_hi) if t.end_open and t.end is not None else new_hi
    df = df.select(*r.keys, new_lo.alias(LO), new_hi.alias(HI)).where(F.col(LO) <= F.col(HI))
    keeps = r.coalesced and (not t.widen or t.start == t.end)
    return r.with_df(df, coalesced=keeps if coalesced is None else coalesced)


def _apply(r: TemporalRelation, op: str, rng: Range) -> TemporalRelation:
    return shift_ends(r, as_transform(op, rng.on(r.timeline)))


def sometime_past(r: TemporalRelation, rng: Range) -> TemporalRelation:
    return _apply(r, "past", rng)


def sometime_future(r: TemporalRelation, rng: Range) -> TemporalRelation:
    return _apply(r, "future", rng)


def always_past(r: TemporalRelation, rng: Range) -> TemporalRelation:
    return _apply(coalesce(r), "alwayspast", rng)


def always_future(r: TemporalRelation, rng: Range) -> TemporalRelation:
    return _apply(coalesce(r), "alwaysfuture", rng)


def shift(r: TemporalRelation, by: int) -> TemporalRelation:
    return shift_ends(r, Transform(by, by))


def close(r: TemporalRelation) -> TemporalRelation:
    """The closure of every interval; never coalesced after, as [0,1) and (1,2] stay two facts."""
    if not r.timeline.dense:
        return r.with_df(r.df.select(*r.keys, _add(F.col(LO), -1).alias(LO), _add(F.col(HI), 1).alias(HI)))
    return r.with_df(r.df.select(*r.keys, _close_start(F.col(LO)).alias(LO), _close_end(F.col(HI)).alias(HI)))


OPERATORS = {"past": sometime_past, "future": sometime_future, "alwayspast": always_past, "alwaysfuture": always_future}


def apply_chain(r: TemporalRelation, ops: list[tuple[str, Range]], placement: str = "minimal", fuse: bool = True) -> TemporalRelation:
    """Operators from the inside out, with a choice of where intervals are coalesced.

    minimal: only right before an always-operator.  earliest: at the input, with a tolerance
    for the gaps that sometime-operators on the way would close, so widening and shrinking
    become one transform of merged facts.  always: at the input and after every operator.
    ``fuse`` composes neighbouring operators of one kind.
    """
    if not ops:
        return r
    steps = [(op, rng.on(r.timeline)) for op, rng in ops]
    if placement == "always":
        r = coalesce(r)
        for op, rng in steps:
            r = coalesce(shift_ends(r, as_transform(op, rng)))
        return r
    moves = [as_transform(op, rng) for op, rng in steps]
    if fuse:
        moves = compose(moves)
    if placement == "earliest" and any(not m.widen for m in moves):
        head = 0
        while moves[head].widen:
            head += 1
        tolerant = compose_gap(moves[:head], r.timeline)
        if tolerant is not None:
            r = coalesce(r, tolerant)
            for m in moves[:head]:
                r = shift_ends(r, m, coalesced=True)
            moves = moves[head:]
    for m in moves:
        r = shift_ends(r if m.widen else coalesce(r), m)
    return r


def compose(moves: list[Transform]) -> list[Transform]:
    """Neighbours of one kind are one move: sums of the ends, open where either is."""
    out: list[Transform] = []
    for m in moves:
        p = out[-1] if out else None
        if p and p.widen == m.widen:
            start = None if p.start is None or m.start is None else p.start + m.start
            end = None if p.end is None or m.end is None else p.end + m.end
            out[-1] = Transform(start, end, p.start_open or m.start_open, p.end_open or m.end_open, m.widen)
        else:
            out.append(m)
    return out


def compose_gap(moves: list[Transform], timeline) -> int | None:
    """Missing cells that widening by closed, bounded moves closes; None where no such number exists."""
    total = 0
    for m in moves:
        if m.start is None or m.end is None or m.start_open or m.end_open:
            return None
        total += timeline.scale * (m.end - m.start)
    return total
