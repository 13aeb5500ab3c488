"""Joins of facts that hold together, interval difference, and relatives."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import HI, LO, NEG, POS, TemporalRelation
from .merge import coalesce, gaps_of


MEET = f"l.{LO} <= r.{HI} and r.{LO} <= l.{HI}"


def _meet(l: str, r: str):
    return (F.col(f"{l}.{LO}") <= F.col(f"{r}.{HI}")) & (F.col(f"{r}.{LO}") <= F.col(f"{l}.{HI}"))


def _joined(left: DataFrame, right: DataFrame, on, out_keys, hint: str | None) -> DataFrame:
    l, r = left.alias("l"), (right.hint(hint) if hint else right).alias("r")
    condition = " and ".join([*(f"l.`{k}` = r.`{k}`" for k in on), MEET])
    own = set(left.columns)
    lk = [f"l.`{k}`" for k in out_keys if k in own]
    rk = [f"r.`{k}`" for k in out_keys if k not in own]
    return l.join(r, F.expr(condition)).selectExpr(*lk, *rk, f"greatest(l.{LO}, r.{LO}) as {LO}", f"least(l.{HI}, r.{HI}) as {HI}")


def temporal_join(r: TemporalRelation, s: TemporalRelation, on: list[str], hint: str | None = None, bucket: int | None = None) -> TemporalRelation:
    """Facts with equal join keys over the intersection of their intervals; empty ones go.

    Without keys only the intervals are matched; then both sides are dealt over time buckets,
    so the join is still by equality.  ``bucket`` (cells) sets their width.
    """
    keys = [*r.keys, *(k for k in s.keys if k not in r.keys)]
    shared = [k for k in s.keys if k in r.keys and k not in on]
    if shared:
        raise ValueError(f"columns {shared} of both sides are not join keys; rename them")
    if not on:
        return bucket_join(r, s, bucket)
    df = _joined(r.df, s.df, on, keys, hint)
    return r.with_df(df, keys, r.coalesced and s.coalesced)


def _ends(r: TemporalRelation):
    finite = (F.col(LO) > NEG) & (F.col(HI) < POS)
    return r.df.agg(
        F.min(F.when(F.col(LO) > NEG, F.col(LO))).alias("a"), F.max(F.when(F.col(HI) < POS, F.col(HI))).alias("b"),
        F.avg(F.when(finite, F.col(HI) - F.col(LO))).alias("m"), F.max(F.when(finite, F.col(HI) - F.col(LO))).alias("most"), F.max((~finite).cast("int")).alias("endless"),
    ).first()


def bucket_join(r: TemporalRelation, s: TemporalRelation, bucket: int | None = None, on: list[str] = ()) -> TemporalRelation:
    """A join by overlap (and equal ``on``) over buckets of time, in levels.

    An interval lives on the first level at which it spans few buckets (each level's are 4 times wider, with equal keys 64 times;
    the top one is all of time, for endless facts) and also asks on the levels above; a pair is reported
    only on the higher of its two levels, in the bucket where its intersection starts.  So an interval is copied a few times
    for each level, however long it is.  Without keys those that live on a level meet each other and those that ask there,
    but those that ask never meet each other: a wide bucket would hold nearly all of both sides.
    """
    on, steps = list(on), 64 if on else 4
    keys = [*r.keys, *(k for k in s.keys if k not in r.keys)]
    span, span_s = _ends(r), _ends(s)
    width = bucket or max(1, int(2 * max(span["m"] or 0, span_s["m"] or 0)) + 1)
    longest = max(span["most"] or 0, span_s["most"] or 0)
    widths = [width]
    while widths[-1] < longest:
        widths.append(widths[-1] * steps)
    top = len(widths)
    ends = [x for q in (span, span_s) for x in (q["a"], q["b"]) if x is not None]
    low = min(ends) if ends else 0

    def number(c, level: int):
        return F.floor((c - F.lit(low)) / F.lit(widths[level])).cast("long")

    def at_level(i: int):
        return lambda x: F.struct(F.lit(i).alias("level"), x.alias("b"))

    def dealt(df, side: int):
        finite = (F.col(LO) > NEG) & (F.col(HI) < POS)
        home = F.lit(top)
        for i in reversed(range(top)):
            home = F.when(finite & (F.col(HI) - F.col(LO) <= widths[i]), F.lit(i)).otherwise(home)
        df = df.withColumn("__home", home)
        spots = [F.when(F.col("__home") <= i, F.transform(F.sequence(number(F.col(LO), i), number(F.col(HI), i)), at_level(i))) for i in range(top)]
        if span["endless"] or span_s["endless"]:
            spots.append(F.array(F.struct(F.lit(top).alias("level"), F.lit(0).cast("long").alias("b"))))
        df = df.withColumn("__s", F.explode(F.flatten(F.filter(F.array(*spots), lambda x: x.isNotNull()))))
        if on:
            return df
        # 0: both live here; 1: the left one lives, the right one asks; 2: the other way round.
        lives = F.col("__s.level") == F.col("__home")
        ways = F.when(lives, F.array(F.lit(0), F.lit(1 + side))).otherwise(F.array(F.lit(2 - side)))
        return df.withColumn("__way", F.explode(ways))

    l, q = dealt(r.df, 0).alias("l"), dealt(s.df, 1).alias("r")
    start = F.greatest(f"l.{LO}", f"r.{LO}")
    home = F.lit(0).cast("long")
    for i in reversed(range(top)):
        home = F.when(F.col("l.__s.level") == i, number(start, i)).otherwise(home)
    condition = (F.col("l.__s.level") == F.col("r.__s.level")) & (F.col("l.__s.b") == F.col("r.__s.b")) & _meet("l", "r")
    condition &= (F.col("l.__s.level") == F.greatest("l.__home", "r.__home")) & (F.col("l.__s.b") == home)
    for k in on or ["__way"]:
        condition &= F.col(f"l.{k}") == F.col(f"r.{k}")
    df = l.join(q, condition)
    df = df.select(*(F.col(f"l.{k}").alias(k) for k in r.keys), *(F.col(f"r.{k}").alias(k) for k in s.keys if k not in r.keys), F.greatest(f"l.{LO}", f"r.{LO}").alias(LO), F.least(f"l.{HI}", f"r.{HI}").alias(HI))
    return r.with_df(df, keys, r.coalesced and s.coalesced)


def temporal_join_all(relations: list[TemporalRelation], on: list[list[str]]) -> TemporalRelation:
    out = relations[0]
    for s, keys in zip(relations[1:], on):
        out = temporal_join(out, s, keys)
    return out


def temporal_minus(r: TemporalRelation, s: TemporalRelation, on: list[str]) -> TemporalRelation:
    """The parts of r's intervals where no fact of s with equal keys holds; one interval may become several.

    s is reduced to its keys and coalesced, turned into its gaps, and joined once; facts of r whose
    key s lacks pass whole.  Without keys the gaps are joined over buckets of time.
    """
    if not on:
        other = coalesce(s.with_df(s.df.select(LO, HI), ()))
        cut = bucket_join(r, other.with_df(gaps_of(other), (), True))
        return r.with_df(cut.df, coalesced=r.coalesced)
    other = coalesce(s.select(**{k: k for k in on}))
    l, g = r.df.select(*r.keys, LO, HI).alias("l"), gaps_of(other, marked=True).alias("r")
    condition = reduce(lambda a, b: a & b, [F.col(f"l.{k}") == F.col(f"r.{k}") for k in on], _meet("l", "r"))
    # Every key of s has a marked row over all time, so only facts without any partner lack their key there.
    cut = l.join(g, condition, "left").where("r.__marker is null or not r.__marker")
    none = F.col("r.__marker").isNull()
    lo, hi = F.when(none, F.col(f"l.{LO}")).otherwise(F.greatest(f"l.{LO}", f"r.{LO}")), F.when(none, F.col(f"l.{HI}")).otherwise(F.least(f"l.{HI}", f"r.{HI}"))
    return r.with_df(cut.select(*(F.col(f"l.{k}").alias(k) for k in r.keys), lo.alias(LO), hi.alias(HI)), coalesced=r.coalesced)


def temporal_semi(r: TemporalRelation, s: TemporalRelation, on: list[str]) -> TemporalRelation:
    """r restricted to when some fact of s with equal keys holds."""
    out = temporal_join(r, coalesce(s.select(**{k: k for k in on})), on)
    return r.with_df(out.df, coalesced=r.coalesced)


def hold_until_next(df: DataFrame, keys, at: str, timeline, others=()) -> TemporalRelation:
    """Readings that stay valid until the next one of their series; the last one stays for ever."""
    w = Window.partitionBy(*keys).orderBy(at)
    ended = df.withColumn("__next", F.lead(at).over(w))
    lo, hi = timeline.encode(F.col(at), F.col("__next"), False, F.col("__next").isNotNull())
    out = ended.select(*keys, *others, lo.alias(LO), hi.alias(HI)).where(F.col(LO) <= F.col(HI))
    return TemporalRelation(out, (*keys, *others), timeline)


def sweep(r: TemporalRelation, by: list[str]) -> DataFrame:
    """How many facts of a group hold, as (by, __lo, n) at each cell where the number changes."""
    ends = r.df.select(*by, F.col(LO).alias("__at"), F.lit(1).alias("d")).unionByName(r.df.where(F.col(HI) < POS).select(*by, (F.col(HI) + 1).alias("__at"), F.lit(-1).alias("d")))
    steps = ends.groupBy(*by, "__at").agg(F.sum("d").alias("d")).where("d <> 0")
    w = Window.partitionBy(*[F.col(k) for k in by] or [F.lit(0)]).orderBy("__at")
    return steps.select(*by, F.col("__at").alias(LO), F.sum("d").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("n"))


def interval_union(r: TemporalRelation, s: TemporalRelation) -> TemporalRelation:
    return coalesce(r.with_df(r.df.select(*r.keys, LO, HI).unionByName(s.df.select(*r.keys, LO, HI))))


def interval_intersect(r: TemporalRelation, s: TemporalRelation) -> TemporalRelation:
    return temporal_join(coalesce(r), coalesce(s), list(r.keys))


def interval_except(r: TemporalRelation, s: TemporalRelation) -> TemporalRelation:
    return temporal_minus(coalesce(r), s, list(r.keys))


RELATIONS = ("before", "meets", "overlaps", "finished_by", "contains", "starts", "equals", "started_by", "during", "finishes", "overlapped_by", "met_by", "after")


def relation13(a_lo, a_hi, b_lo, b_hi):
    """Which of the thirteen pairwise relations two non-empty cell ranges have; they meet if no cell lies between."""
    return (
        F.when(a_hi + 1 < b_lo, "before").when(a_hi + 1 == b_lo, "meets").when(b_hi + 1 < a_lo, "after").when(b_hi + 1 == a_lo, "met_by")
        .when((a_lo == b_lo) & (a_hi == b_hi), "equals")
        .when(a_lo == b_lo, F.when(a_hi < b_hi, "starts").otherwise("started_by"))
        .when(a_hi == b_hi, F.when(a_lo > b_lo, "finishes").otherwise("finished_by"))
        .when((a_lo < b_lo) & (a_hi > b_hi), "contains").when((a_lo > b_lo) & (a_hi < b_hi), "during")
        .when(a_lo < b_lo, "overlaps").otherwise("overlapped_by")
    )
