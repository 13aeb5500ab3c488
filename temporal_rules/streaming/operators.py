"""Streams of facts with __lo, __hi in ticks of the time unit of ``at`` (an event-time timestamp).

Sometime-operators are projections.  Merging, always-operators, since and negation keep the
open islands of a key in state; event-time timers drop what the watermark has passed.
"""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import LongType, StringType, StructField, StructType

from ..model import HI, LO, Range, TemporalRelation, Timeline
from ..operators.unary import Transform, as_transform, shift_ends


def stream_diamond(sdf: DataFrame, op: str, rng: Range, scale: int = 1) -> DataFrame:
    """past or future without state: every fact is moved at once."""
    t = as_transform(op, rng)
    if not t.widen or t.start is None or t.end is None:
        raise ValueError("only sometime-operators over bounded ranges are stateless")
    timeline = Timeline(scale == 2)
    t = as_transform(op, rng.on(timeline))
    moved = shift_ends(TemporalRelation(sdf, tuple(c for c in sdf.columns if c not in (LO, HI)), timeline), t)
    return moved.df.select(*sdf.columns)


def _islands(rows: list[list[int]], lo: int, hi: int) -> tuple[list[list[int]], list[int], bool]:
    """Add an interval to sorted islands; the grown island and whether anything changed."""
    for a, b in rows:
        if a <= lo and hi <= b:
            return rows, [a, b], False
    touch = [r for r in rows if r[0] <= hi + 1 and lo <= r[1] + 1]
    grown = [min([lo, *(r[0] for r in touch)]), max([hi, *(r[1] for r in touch)])]
    return sorted([r for r in rows if r not in touch] + [grown]), grown, True


class _Merge(StatefulProcessor):
    """Islands of a key; ``final`` emits an island when the watermark is past it, else every growth at once."""

    def __init__(self, keys: list[str], final: bool, gap: int, shrink: Transform | None, scale: int, ticks_per_ms: float):
        self.keys, self.final, self.gap, self.shrink, self.scale, self.ticks = keys, final, gap, shrink, scale, ticks_per_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("islands", StructType([StructField("v", StringType())]))

    def _load(self) -> list[list[int]]:
        return json.loads(self.state.get()[0]) if self.state.exists() else []

    def _out(self, key, rows) -> pd.DataFrame:
        out = []
        for lo, hi in rows:
            if self.shrink is not None:
                lo, hi = lo + self.scale * self.shrink.start, hi + self.scale * self.shrink.end
                if self.scale == 2:  # an open end of an always-operator closes the result's end
                    lo, hi = (lo - (lo & 1) if self.shrink.start_open else lo), (hi + (hi & 1) if self.shrink.end_open else hi)
            if lo <= hi:
                out.append((*key, lo, hi))
        return pd.DataFrame(out, columns=[*self.keys, LO, HI])

    def _expire(self, now_ms: int) -> list[list[int]]:
        limit = now_ms * self.ticks - self.gap
        rows = self._load()
        gone = [r for r in rows if r[1] < limit]
        if gone:
            kept = [r for r in rows if r[1] >= limit]
            self.state.update((json.dumps(kept),)) if kept else self.state.clear()
        return gone

    def handleInputRows(self, key, rows, timerValues):
        islands, changed = self._load(), []
        for pdf in rows:
            for lo, hi in zip(pdf["lo"].tolist(), pdf["hi"].tolist()):
                islands, grown, new = _islands(islands, int(lo), int(hi))
                if new:
                    changed.append(grown)
        self.state.update((json.dumps(islands),))
        last = max(r[1] for r in islands)
        self.handle.registerTimer(int(last / self.ticks) + int(self.gap / self.ticks) + 2)
        if not self.final:
            yield self._out(key, changed)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        gone = self._expire(expiredTimerInfo.getExpiryTimeInMs())
        if self.final:
            yield self._out(key, gone)
        left = self._load()
        if left:
            self.handle.registerTimer(int(max(r[1] for r in left) / self.ticks) + int(self.gap / self.ticks) + 2)

    def close(self) -> None:
        pass


def _schema(sdf: DataFrame, keys) -> StructType:
    return StructType([*(StructField(k, sdf.schema[k].dataType) for k in keys), StructField(LO, LongType()), StructField(HI, LongType())])


def _named(sdf: DataFrame) -> DataFrame:
    """State functions get rows as named tuples, whose names do not start with an underscore."""
    return sdf.withColumnsRenamed({LO: "lo", HI: "hi"})


def stream_merge(sdf: DataFrame, keys: list[str], mode: str = "update", gap: int = 0, ticks_per_ms: float = 1.0) -> DataFrame:
    """Coalescing on a stream that has a watermark: ``update`` refines at once, ``append`` emits islands the watermark has closed.

    Facts later than the watermark are dropped by the engine before they get here.
    """
    p = _Merge(keys, mode == "append", gap, None, 1, ticks_per_ms)
    return _named(sdf).groupBy(*keys).transformWithStateInPandas(p, outputStructType=_schema(sdf, keys), outputMode="Append" if mode == "append" else "Update", timeMode="EventTime")


def stream_box(sdf: DataFrame, keys: list[str], op: str, rng: Range, scale: int = 1, ticks_per_ms: float = 1.0, mode: str = "update") -> DataFrame:
    """An always-operator: merge, then shrink.  In update mode a part that is long enough is emitted at once, as
    later facts can only lengthen it; append mode waits for the watermark.  ``scale`` is 2 on a dense timeline's cells."""
    t = as_transform(op, rng.on(Timeline(scale == 2)))
    if t.widen or t.start is None or t.end is None:
        raise ValueError("an always-operator over a bounded range")
    p = _Merge(keys, mode == "append", 0, t, scale, ticks_per_ms)
    return _named(sdf).groupBy(*keys).transformWithStateInPandas(p, outputStructType=_schema(sdf, keys), outputMode="Append" if mode == "append" else "Update", timeMode="EventTime")


def stream_join(left: DataFrame, right: DataFrame, on: list[str], at_left: str, at_right: str, within: str) -> DataFrame:
    """Facts of two watermarked streams that overlap and start within a bounded time of each other, so state is evicted."""
    l, r = left.alias("l"), right.alias("r")
    condition = (F.col(f"l.{LO}") <= F.col(f"r.{HI}")) & (F.col(f"r.{LO}") <= F.col(f"l.{HI}"))
    condition &= (F.col(f"l.{at_left}") >= F.col(f"r.{at_right}") - F.expr(f"interval {within}")) & (F.col(f"l.{at_left}") <= F.col(f"r.{at_right}") + F.expr(f"interval {within}"))
    for k in on:
        condition &= F.col(f"l.{k}") == F.col(f"r.{k}")
    rest = [F.col(f"r.{c}") for c in right.columns if c not in (*on, LO, HI, at_right)]
    own = [F.col(f"l.{c}") for c in left.columns if c not in (LO, HI, at_left)]
    return l.join(r, condition).select(*own, *rest, F.greatest(f"l.{LO}", f"r.{LO}").alias(LO), F.least(f"l.{HI}", f"r.{HI}").alias(HI))


class _Ordered(StatefulProcessor):
    """Both sides' facts wait until the watermark is past what an answer needs; then the closed time is answered and all
    that no later answer can read is dropped, so a key that never pauses keeps a bounded state.

    The answer at an instant reads from ``before`` ticks earlier to ``after`` ticks later.  Facts that are cut leave an
    island that begins one tick before what is kept, so what held throughout still does.
    """

    def __init__(self, keys: list[str], kind: str, rng: tuple[int, int], ticks_per_ms: float):
        self.keys, self.kind, self.range, self.ticks = keys, kind, rng, ticks_per_ms
        self.before = rng[1] + 1 if kind == "since" else 0
        self.after = rng[1] + 1 if kind == "until" else 0

    def init(self, handle):
        self.handle = handle
        self.state = handle.getValueState("rows", StructType([StructField("v", StringType())]))

    def _load(self):
        return json.loads(self.state.get()[0]) if self.state.exists() else {"l": [], "r": [], "done": None}

    def _wait(self, kept, now_ms):
        """A timer for when the first instant that is not answered yet will be closed."""
        ends = [x[1] for v in (kept["l"], kept["r"]) for x in v]
        if ends:
            first = min(x[0] for v in (kept["l"], kept["r"]) for x in v)
            first = max(first, kept["done"] + 1) if kept["done"] is not None else first
            last = max(ends) + self.before + self.after
            if first <= last:
                self.handle.registerTimer(max(int((first + self.after) / self.ticks) + 2, now_ms + 1))

    def handleInputRows(self, key, rows, timerValues):
        kept = self._load()
        for pdf in rows:
            for side, lo, hi in zip(pdf["side"], pdf["lo"], pdf["hi"]):
                kept[side], _, _ = _islands(kept[side], int(lo), int(hi))
        self.state.update((json.dumps(kept),))
        self._wait(kept, timerValues.getCurrentWatermarkInMs())
        return iter(())

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        kept = self._load()
        now = max(expiredTimerInfo.getExpiryTimeInMs(), timerValues.getCurrentWatermarkInMs())
        closed = int(now * self.ticks) - 1 - self.after  # facts that may still come begin later
        start = kept["done"]
        got = [[max(lo, start + 1) if start is not None else lo, min(hi, closed)] for lo, hi in answer(self.kind, kept["l"], kept["r"], self.range)]
        keep = closed - self.before  # instants up to here are read by no later answer
        rest = {side: [[max(lo, keep - 1), hi] for lo, hi in kept[side] if hi >= keep] for side in ("l", "r")}
        rest["done"] = closed if start is None else max(start, closed)
        if rest["l"] or rest["r"]:
            self.state.update((json.dumps(rest),))
            self._wait(rest, now)
        else:
            self.state.clear()
        got = [g for g in got if g[0] <= g[1]]
        if got:
            yield pd.DataFrame([(*key, lo, hi) for lo, hi in got], columns=[*self.keys, LO, HI])

    def close(self):
        pass


def answer(kind: str, left: list[list[int]], right: list[list[int]], rng: tuple[int, int]) -> list[list[int]]:
    """minus: left without right.  since and until on integer ticks over coalesced islands: right moved by the range as
    far as left lasts, and right itself where the range holds 0, its neighbour where it holds 1."""
    out: list[list[int]] = []
    if kind == "minus":
        for lo, hi in left:
            for a, b in right:
                if a <= hi and lo <= b:
                    if lo < a:
                        out, _, _ = _islands(out, lo, a - 1)
                    lo = b + 1
            if lo <= hi:
                out, _, _ = _islands(out, lo, hi)
        return out
    sign = 1 if kind == "since" else -1
    for a, b in right:
        for x in (0, 1):
            if rng[0] <= x <= rng[1]:
                out, _, _ = _islands(out, a + sign * x, b + sign * x)
        for lo, hi in left:
            c, d = max(a, lo - 1), min(b, hi + 1)
            if c <= d:
                moved = (c + rng[0], d + rng[1]) if sign > 0 else (c - rng[1], d - rng[0])
                e, f = max(moved[0], lo - 1), min(moved[1], hi + 1)
                if e <= f:
                    out, _, _ = _islands(out, e, f)
    return out


def _two_sided(left: DataFrame, right: DataFrame, keys, kind: str, rng: tuple[int, int], ticks_per_ms: float) -> DataFrame:
    both = left.withColumn("side", F.lit("l")).unionByName(right.withColumn("side", F.lit("r")))
    p = _Ordered(keys, kind, rng, ticks_per_ms)
    return _named(both).groupBy(*keys).transformWithStateInPandas(p, outputStructType=_schema(left, keys), outputMode="Append", timeMode="EventTime")


def stream_minus(left: DataFrame, right: DataFrame, keys: list[str], ticks_per_ms: float = 1.0) -> DataFrame:
    return _two_sided(left, right, keys, "minus", (0, 0), ticks_per_ms)


def stream_since(a: DataFrame, b: DataFrame, keys: list[str], rng: Range, ticks_per_ms: float = 1.0) -> DataFrame:
    return _two_sided(a, b, keys, "since", (rng.lo + rng.lo_open, rng.hi - rng.hi_open), ticks_per_ms)


def stream_until(a: DataFrame, b: DataFrame, keys: list[str], rng: Range, ticks_per_ms: float = 1.0) -> DataFrame:
    return _two_sided(a, b, keys, "until", (rng.lo + rng.lo_open, rng.hi - rng.hi_open), ticks_per_ms)


def session_merge(sdf: DataFrame, keys: list[str], ts: str, gap: str) -> DataFrame:
    """sometime-past over [0, gap) of punctual facts, merged: Spark's session windows."""
    return sdf.groupBy(*keys, F.session_window(ts, gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(*keys, F.unix_micros("w.start").alias("t_start"), F.unix_micros("w.end").alias("t_end"), "n")


def windowed(sdf: DataFrame, keys: list[str], ts: str, size: str, slide: str | None = None) -> DataFrame:
    """Fixed windows (one calendar unit) or sliding ones (rolling) with the usual aggregates."""
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    return sdf.groupBy(*keys, w.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"), F.avg("value").alias("mean")).select(*keys, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "total", "mean")
