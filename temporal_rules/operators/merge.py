"""Coalescing of touching intervals, in its strategies."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import HI, LO, NEG, POS, TemporalRelation


def _names(keys) -> str:
    return "".join(f"`{k}`, " for k in keys)


def _islands(df: DataFrame, keys, gap: int) -> DataFrame:
    """One statement: a plan is analysed once, which counts where rounds are many."""
    k, part = _names(keys), ", ".join(f"`{x}`" for x in keys) or "0"
    return df.sparkSession.sql(
        f"""select {k}min({LO}) as {LO}, max({HI}) as {HI} from (
          select *, sum(__new) over (partition by {part} order by {LO}, {HI} rows between unbounded preceding and current row) as __island from (
            select {k}{LO}, {HI}, if({LO} <= max({HI}) over (partition by {part} order by {LO}, {HI} rows between unbounded preceding and 1 preceding) + {1 + gap}, 0, 1) as __new from {{df}}))
        group by {k}__island""",
        df=df,
    )


def coalesce(r: TemporalRelation, gap: int = 0, force: bool = False, hot: int | None = None) -> TemporalRelation:
    """Unions of overlapping and adjacent intervals per key: one exchange and one sort on the keys.

    ``gap`` also bridges so many missing cells.  A relation known to be coalesced is returned as it is.
    ``hot`` counts facts per key first and, where a key has more than so many, deals it over buckets of time.
    """
    if r.coalesced and not gap and not force:
        return r
    if hot and not gap and (bucket := hot_bucket(r, hot)):
        return coalesce_hot(r, bucket)
    return r.with_df(_islands(r.df.select(*r.keys, LO, HI), r.keys, gap), coalesced=True)


def coalesce_hot(r: TemporalRelation, bucket: int) -> TemporalRelation:
    """The same islands where one key has very many facts: no task sees more of a key than a bucket of starts.

    Running maxima are taken within (key, bucket of the start); what comes over from earlier buckets
    is a running maximum over one row for each bucket.
    """
    keys = [*r.keys, "__bucket"]
    width = int(bucket)
    df = r.df.select(*r.keys, LO, HI, F.when(F.col(LO) <= NEG, F.lit(NEG)).otherwise(F.floor(F.col(LO) / width)).cast("long").alias("__bucket"))
    inner = Window.partitionBy(*keys).orderBy(LO, HI)
    along = (Window.partitionBy(*r.keys) if r.keys else Window.partitionBy(F.lit(0))).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)

    def carried(d: DataFrame, value, name: str) -> DataFrame:
        """d with the greatest value of the key's earlier buckets."""
        top = d.groupBy(*keys).agg(F.max(value).alias("__top"))
        before = top.select(*keys, F.max("__top").over(along).alias(name))
        l, q = d.alias("l"), before.alias("q")
        on = F.col("l.__bucket") == F.col("q.__bucket")
        for k in r.keys:
            on &= F.col(f"l.{k}").eqNullSafe(F.col(f"q.{k}"))
        return l.join(q, on).select("l.*", f"q.{name}")

    df = carried(df, F.col(HI), "__over")
    reach = F.greatest("__over", F.max(HI).over(inner.rowsBetween(Window.unboundedPreceding, -1)))
    df = df.withColumn("__start", F.when(reach.isNull() | (F.col(LO) > reach + 1), F.col(LO))).drop("__over")
    df = carried(df, F.col("__start"), "__from")
    start = F.greatest("__from", F.max("__start").over(inner.rowsBetween(Window.unboundedPreceding, 0)))
    df = df.select(*r.keys, start.alias("__island"), HI).groupBy(*r.keys, "__island").agg(F.max(HI).alias(HI))
    return r.with_df(df.select(*r.keys, F.col("__island").alias(LO), HI), coalesced=True)


def hot_bucket(r: TemporalRelation, most: int) -> int | None:
    """A bucket width at which the largest key's facts are dealt over parts of about ``most``; None where no key has more."""
    by = [F.col(k) for k in r.keys] or [F.lit(0).alias("__all")]
    finite = F.when(F.col(LO) > NEG, F.col(LO))
    top = r.df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.min(finite).alias("a"), F.max(finite).alias("b")).orderBy(F.desc("n")).first()
    if top is None or top["n"] <= most or top["a"] is None:
        return None
    return max(1, (top["b"] - top["a"]) * most // top["n"])


def stream_states(r: TemporalRelation, arrival: str) -> TemporalRelation:
    """The streaming strategy in batch form: every fact in order of arrival is merged with what its key has
    seen and the grown interval is forwarded at once, so results may be subsumed by later ones.

    A key's facts stand together after one exchange and one sort; a key's first fact passes as it is, so
    only facts after it are looked at one by one.
    """
    from bisect import bisect_left, bisect_right

    import pyarrow as pa

    keys, names = list(r.keys), [*r.keys, LO, HI]

    def grow(batches):
        starts: list[int] = []  # what the last key has seen: islands in order
        ends: list[int] = []
        for batch in batches:
            lo, hi = (batch.column(c).to_numpy().copy() for c in (LO, HI))
            later = batch.column("__nth").to_numpy() > 1
            keep = later | True
            last = -1
            for i in later.nonzero()[0].tolist():
                if i and i - 1 != last:
                    starts, ends = [int(lo[i - 1])], [int(hi[i - 1])]
                last = i
                a, b = int(lo[i]), int(hi[i])
                x, y = bisect_left(ends, a - 1), bisect_right(starts, b + 1)
                if x + 1 == y and starts[x] <= a and b <= ends[x]:
                    keep[i] = False
                    continue
                if x < y:
                    a, b = min(a, starts[x]), max(b, ends[y - 1])
                starts[x:y], ends[x:y] = [a], [b]
                lo[i], hi[i] = a, b
            if len(later) and last != len(later) - 1:
                starts, ends = [int(lo[-1])], [int(hi[-1])]
            cols = [*(batch.column(k) for k in keys), pa.array(lo), pa.array(hi)]
            yield pa.RecordBatch.from_arrays(cols, names).filter(pa.array(keep))

    nth = Window.partitionBy(*[F.col(k) for k in keys] or [F.lit(0)]).orderBy(F.col(arrival).asc_nulls_last(), LO, HI)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in r.df.select(*names).schema)
    return r.with_df(r.df.select(*names, F.row_number().over(nth).alias("__nth")).mapInArrow(grow, schema))


def novel(delta: TemporalRelation, known: TemporalRelation) -> TemporalRelation:
    """What a delta adds to what is known, piece by piece (the change flag of a merge).

    Both sides' ends are swept together, so one exchange and one sort on the keys merge the delta and
    subtract what is known; neither side need be coalesced.
    """
    k, part = _names(delta.keys), ", ".join(f"`{x}`" for x in delta.keys)
    order = f"partition by {part or '0'} order by"
    run = "rows between unbounded preceding and current row"
    own = known.df.toDF(*delta.keys, LO, HI) if known.keys != delta.keys else known.df

    def ends(d: int, n: int, source: str) -> str:
        # An endless fact has no end to sweep; every other one has two.
        return f"select {k}inline(array(struct({LO} as __at, {d} as __d, {n} as __k), struct(if({HI} < {POS}, {HI} + 1, null) as __at, {-d} as __d, {-n} as __k))) from {{{source}}}"

    # Ties leave pieces of no length, so the ends need not be summed up first; one order serves all three windows.
    out = delta.df.sparkSession.sql(
        f"""select {k}min(__at) as {LO}, max({HI}) as {HI} from (
          select *, sum(if(__fresh and not __before, 1, 0)) over ({order} __at {run}) as __island from (
            select *, lag(__fresh, 1, false) over ({order} __at) as __before from (
              select {k}__at, coalesce(lead(__at) over ({order} __at) - 1, {POS}) as {HI}, sum(__d) over ({order} __at {run}) > 0 and sum(__k) over ({order} __at {run}) = 0 as __fresh
              from (select {f'/*+ repartition({part}) */ ' if part else ''}* from ({ends(1, 0, 'delta')} union all {ends(0, 1, 'known')}) where __at is not null))
            where __at <= {HI}))
        where __fresh group by {k}__island""",
        delta=delta.df, known=own,
    )
    return delta.with_df(out, coalesced=True)


def gaps_of(r: TemporalRelation, marked: bool = False) -> DataFrame:
    """The complement per key, from -inf to inf, of a coalesced relation.

    ``marked`` adds a column __marker and for every key a row over all time where it is true.  Without
    keys an empty relation has one gap, over all time.
    """
    part = [F.col(k) for k in r.keys] or [F.lit(0)]
    w = Window.partitionBy(*part).orderBy(LO)
    df = r.df.select(*r.keys, LO, HI, F.lead(LO).over(w).alias("__next"), (F.row_number().over(w) == 1).alias("__first"))
    piece = lambda a, b, when, mark=False: F.when(when, F.struct(a.alias("a"), b.alias("b"), F.lit(mark).alias("__marker")))
    end = F.coalesce(F.col("__next") - 1, F.lit(POS))
    pieces = [piece(F.col(HI) + 1, end, (F.col(HI) < POS) & (F.col(HI) + 1 <= end)), piece(F.lit(NEG), F.col(LO) - 1, F.col("__first") & (F.col(LO) > NEG))]
    if marked:
        pieces.append(piece(F.lit(NEG), F.lit(POS), F.col("__first"), True))
    out = df.select(*r.keys, F.explode(F.filter(F.array(*pieces), lambda x: x.isNotNull())).alias("__g"))
    out = out.select(*r.keys, F.col("__g.a").alias(LO), F.col("__g.b").alias(HI), F.col("__g.__marker").alias("__marker"))
    if not r.keys:
        none = r.df.agg(F.count(F.lit(1)).alias("n")).where("n = 0")
        out = out.unionByName(none.select(F.lit(NEG).alias(LO), F.lit(POS).alias(HI), F.lit(False).alias("__marker")))
    return out if marked else out.drop("__marker")
