"""Aggregates at every instant, over all time, monotonic, and by calendar unit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import HI, LO, POS, TemporalRelation
from .joins import bucket_join
from .merge import coalesce


def agg_at_each_time(r: TemporalRelation, by: list[str], f: str, value: str | None = None, out: str = "value", merge: bool = True) -> TemporalRelation:
    """One fact for every stretch of time on which a group's aggregate is constant.

    A contributor is a whole row of keys: its touching facts count once.  Instants without
    facts give none.  sum, count and avg are running sums over interval ends; min and max look
    at the facts of each elementary stretch.
    """
    r = coalesce(r)
    part = [F.col(k) for k in by] or [F.lit(0)]
    v = F.col(value) if value else F.lit(1)
    if f in ("sum", "count", "avg"):
        exact = v.cast("decimal(28,6)") if f != "count" else F.lit(1).cast("decimal(28,6)")
        # Both ends of a fact from one reading of it; an endless one has no end.
        end = lambda at, n, x: F.struct(at.alias("__at"), F.lit(n).alias("__n"), x.alias("__s"))
        both = F.array(end(F.col(LO), 1, exact), end(F.when(F.col(HI) < POS, F.col(HI) + 1), -1, -exact))
        # A group's running sum is one task's work; dealt by group before its facts are split into ends, nothing is exchanged after.
        facts = r.df.repartition(*by) if by else r.df
        ends = facts.select(*by, F.inline(both)).where("__at is not null")
        steps = ends.groupBy(*by, "__at").agg(F.sum("__n").alias("__n"), F.sum("__s").alias("__s"))
        w = Window.partitionBy(*part).orderBy("__at")
        run = w.rowsBetween(Window.unboundedPreceding, 0)
        seg = steps.select(*by, F.col("__at").alias(LO), F.coalesce(F.lead("__at").over(w) - 1, F.lit(POS)).alias(HI), F.sum("__n").over(run).alias("__n"), F.sum("__s").over(run).alias("__s")).where("__n > 0")
        got = {"sum": F.col("__s"), "count": F.col("__n").cast("long"), "avg": F.col("__s") / F.col("__n")}[f]
        df = seg.select(*by, got.alias(out), LO, HI)
        if merge:
            # A group's stretches are in order already: equal ones that touch are neighbours, so nothing is exchanged for them.
            w = Window.partitionBy(*part).orderBy(LO)
            same = (F.lag(HI).over(w) + 1 == F.col(LO)) & F.lag(out).over(w).eqNullSafe(F.col(out))
            df = df.withColumn("__new", F.when(same, 0).otherwise(1))
            df = df.withColumn("__island", F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
            df = df.groupBy(*by, "__island").agg(F.first(out).alias(out), F.min(LO).alias(LO), F.max(HI).alias(HI)).select(*by, out, LO, HI)
            return r.with_df(df, (*by, out), True)
    else:
        cuts = r.df.select(*by, F.col(LO).alias("__at")).unionByName(r.df.where(F.col(HI) < POS).select(*by, (F.col(HI) + 1).alias("__at"))).distinct()
        w = Window.partitionBy(*part).orderBy("__at")
        seg = cuts.select(*by, F.col("__at").alias(LO), F.coalesce(F.lead("__at").over(w) - 1, F.lit(POS)).alias(HI))
        # A stretch meets the facts near it only: both are dealt over buckets of time within the group.
        facts = r.with_df(r.df.select(*by, F.col(value).alias("__v"), LO, HI), (*by, "__v"))
        met = bucket_join(r.with_df(seg, by), facts, on=by)
        df = met.df.groupBy(*by, LO, HI).agg((F.min if f == "min" else F.max)("__v").alias(out)).select(*by, out, LO, HI)
    res = r.with_df(df, (*by, out))
    return coalesce(res) if merge else res


def agg_across_time(r: TemporalRelation, by: list[str], **aggs: Column) -> DataFrame:
    """Aggregates over a group's whole history."""
    return r.df.groupBy(*by).agg(*(c.alias(n) for n, c in aggs.items()))


def best_at_each_time(r: TemporalRelation, by: list[str], value: str, out: str, least: bool = False) -> TemporalRelation:
    """The greatest (or least) value of a group for every stretch of time on which it is constant, coalesced.

    One exchange and one sort: a group's facts are swept in order of their starts, and only those that hold at the
    moment are remembered.  Most groups that a contributor makes have one fact, which passes as it is.
    Nulls count only where nothing else holds; NaN is greater than any number.
    """
    import pyarrow as pa

    names = [*by, out, LO, HI]

    def sweep(batches):
        from heapq import heappop, heappush

        class Entry(tuple):
            """(order, end, value): the one that holds comes first in the heap, of equal ones the longest."""

            def __lt__(self, other):
                return self[1] > other[1] if self[0] == other[0] else self[0] < other[0] if least else self[0] > other[0]

        def order(v):
            if v is None:
                return (3,) if least else (0,)
            return (2,) if v != v else (1, v)

        heap, at, run, key, found = [], None, None, 0, []  # of the group at hand

        def advance(end):
            """Stretches from ``at`` to ``end`` go to the run, which ends where the best value changes."""
            nonlocal at, run
            while heap and at <= end:
                if heap[0][1] < at:
                    heappop(heap)
                    continue
                o, last, v = heap[0]
                last = min(last, end)
                if run and run[0] == o and run[3] + 1 == at:
                    run = (o, run[1], run[2], last)
                else:
                    close()
                    run = (o, v, at, last)
                at = last + 1

        def close():
            nonlocal run
            if run:
                found.append((key, *run[1:]))
            run = None

        def told(rows, kind):
            """What was found, with the keys of the rows it was found for."""
            got = rows.select(by).take(pa.array([f[0] for f in found], pa.int64())) if by else None
            cols = [pa.array([f[1] for f in found], kind), pa.array([f[2] for f in found], pa.int64()), pa.array([f[3] for f in found], pa.int64())]
            return pa.RecordBatch.from_arrays([*(got.columns if by else []), *cols], names)

        rest = None  # the last row: the open group's keys
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = batch if rest is None else pa.Table.from_batches([rest, batch]).combine_chunks().to_batches()[0]
            first = rows.column("__nth").to_numpy() == 1
            new = int(rest is not None)
            key = 0
            alone = first.copy()
            alone[:-1] &= first[1:]
            alone[-1] = False  # its group may go on
            if new:
                alone[0] = False
            slow = (~alone).nonzero()[0][new:]
            values = rows.column(out).take(pa.array(slow)).to_pylist()
            lo, hi = (rows.column(c).to_numpy() for c in (LO, HI))
            for i, v in zip(slow.tolist(), values):
                if first[i]:
                    advance(float("inf"))
                    close()
                    heap.clear()
                    key = i
                a = int(lo[i])
                if not first[i]:
                    advance(a - 1)
                if first[i] or not heap:
                    at = a
                heappush(heap, Entry((order(v), int(hi[i]), v)))
            yield pa.RecordBatch.from_arrays(rows.filter(pa.array(alone)).select(names).columns, names)
            if found:
                yield told(rows, rows.column(out).type)
                found.clear()
            rest = rows.slice(rows.num_rows - 1)
        if rest is not None:
            key = 0
            advance(float("inf"))
            close()
            if found:
                yield told(rest, rest.column(out).type)

    df = r.df.select(*by, F.col(value).alias(out), LO, HI)
    nth = Window.partitionBy(*[F.col(k) for k in by] or [F.lit(0)]).orderBy(LO)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    return r.with_df(df.withColumn("__nth", F.row_number().over(nth)).mapInArrow(sweep, schema), (*by, out), True)


def monotonic(r: TemporalRelation, by: list[str], f: str, value: str, contributor: list[str], out: str = "value") -> TemporalRelation:
    """Every contributor counts by its best value at an instant: the greatest for msum, mcount and mmax, the least for mmin."""
    contributor = [c for c in contributor if c not in by]
    best = best_at_each_time(r, [*by, *contributor], value, "__best", f == "mmin")
    plain = {"msum": "sum", "mcount": "count", "mmin": "min", "mmax": "max"}[f]
    return agg_at_each_time(best, by, plain, "__best", out)


def covered_time(r: TemporalRelation, by: list[str]) -> DataFrame:
    """Ticks covered by any fact of a group (dense: length; discrete: number of ticks)."""
    m = coalesce(r.select(**{k: k for k in by}))
    if r.timeline.dense:
        length = F.shiftright(F.col(HI) + 1, 1) - F.shiftright(F.col(LO), 1)
    else:
        length = F.col(HI) - F.col(LO) + 1
    return m.df.groupBy(*by).agg(F.sum(length).alias("covered"))


def lift_to_unit(r: TemporalRelation, unit: str, epoch: str = "1995-01-01") -> TemporalRelation:
    """Facts of a day timeline become valid over every whole unit that they touch."""
    step = {"month": F.expr("interval 1 month"), "year": F.expr("interval 1 year"), "week": F.expr("interval 7 days"), "quarter": F.expr("interval 3 months")}[unit]
    day0 = F.lit(epoch).cast("date")
    first = F.floor(F.col(LO) / r.timeline.scale).cast("int")
    last = F.floor(F.col(HI) / r.timeline.scale).cast("int")
    a = F.trunc(F.date_add(day0, first), unit)
    b = F.trunc(F.date_add(day0, last), unit)
    df = r.df.withColumn("__u", F.explode(F.sequence(a, b, step)))
    start = F.datediff(F.col("__u"), day0).cast("long")
    end = F.datediff((F.col("__u") + step).cast("date"), day0).cast("long")
    lo, hi = r.timeline.encode(start, end if r.timeline.dense else end - 1, False, r.timeline.dense)
    return coalesce(r.with_df(df.select(*r.keys, lo.alias(LO), hi.alias(HI))))


def rollup_units(df: DataFrame, day: Column, value: Column) -> DataFrame:
    """Sums by year, month and day with all their subtotals."""
    return df.select(F.year(day).alias("y"), F.month(day).alias("m"), value.alias("v")).rollup("y", "m").agg(F.sum("v").alias("total"), F.count(F.lit(1)).alias("n"))
