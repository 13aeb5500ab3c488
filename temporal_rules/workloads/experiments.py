"""The experiment families: each yields rows of (family, variant, size, seconds, rows, note).

    python -m temporal_rules.workloads.experiments SF_DIR [FAMILY...]
"""

from __future__ import annotations

import sys
import time

from pyspark.sql import functions as F

from .. import baselines
from ..functions import timeseries as ts
from ..model import HI, LO, Range, TemporalRelation
from ..operators import joins, merge, unary
from ..plans.runtime import Engine, Options
from . import base as b
from . import queries as q


def timed(df):
    t = time.time()
    n = df.count()
    return time.time() - t, n


def share(r: TemporalRelation, percent: int) -> TemporalRelation:
    return r.with_df(r.df.where(F.pmod(F.xxhash64(*r.keys, LO), F.lit(100)) < percent))


def ownership(spark, sf):
    """Every ownership program; merge placements of the box program."""
    for name in ("own_temporal", "own_negation", "own_aggregation", "own_diamond", "own_box_minimal", "own_box_earliest", "own_box_always"):
        s, n = timed(q.QUERIES[name](spark, sf))
        yield "ownership", name, sf, s, n, ""


def rivals(spark, sf):
    """Semi-naive and naive rounds, fused and unfused chains."""
    facts = lambda: {"seed": b.seed(spark, sf), "big": b.big(spark, sf), "linked": b.linked(spark, sf)}
    program = "watch(Z) :- seed(Z).\n" + q.OWN_DIAMOND
    for name, o in (("seminaive", Options()), ("naive", Options(strategy="naive")), ("seminaive unfused", Options(fuse=False)), ("merge always", Options(placement="always"))):
        t = time.time()
        e = Engine(program, facts(), o).run()
        yield "rivals", name, sf, time.time() - t, sum(sum(v) for v in e.report.rounds.values()), f"rounds {len(e.report.rounds['watch'])}"


def hierarchy(spark, sf):
    """Non-recursive and recursive programs over 25 to 100 % of the orders."""
    for percent in (25, 50, 75, 100):
        facts = q._hier_facts(spark, sf)
        facts["placed"] = share(facts["placed"], percent)
        s, n = timed(Engine(q.HIER, facts).query("hot").df)
        yield "hierarchy", "non-recursive", percent, s, n, ""
    s, n = timed(q.QUERIES["hier_affected"](spark, sf))
    yield "hierarchy", "recursive", 100, s, n, ""


def stations(spark, sf):
    """Both weather programs over 5, 50 and all stations."""
    for most in (5, 50, None):
        r = b.reading(spark, sf)
        r = r if most is None else r.where(F.col("user_id") < most)
        for name, rules, goal in (("W1", f"above(U) :- reading(U, V), V > 50. high(U) :- alwayspast[0,{6 * b.HOUR}] above(U).", "high"), ("W2", f"strong(U) :- reading(U, V), V > 110. quiet(U) :- reading(U, V), V < 5. gust(U) :- past[0,{24 * b.HOUR}] strong(U), not quiet(U).", "gust")):
            s, n = timed(Engine(rules, {"reading": r}).query(goal).df)
            yield "stations", name, most or "all", s, n, ""


def generator(spark, sf, sizes=(1_000, 10_000, 100_000, 1_000_000)):
    for n in sizes:
        for program in ("box", "diamond", "union", "intersection"):
            s, rows = timed(q.generated(spark, n, program))
            yield "generator", program, n, s, rows, ""


def merging(spark, sf):
    """Blocking, streaming and two-level merging of the same facts; gap-tolerant merge with one transform against three placements."""
    r = b.pairs(spark, sf, 0)
    stamped = r.with_df(r.df.withColumn("seq", F.xxhash64("cust", "supp", LO, HI)))
    for name, make in (("blocking", lambda: merge.coalesce(r)), ("two-level", lambda: merge.coalesce_hot(r, 400)), ("streaming", lambda: merge.stream_states(stamped, "seq"))):
        s, n = timed(make().df)
        yield "merging", name, sf, s, n, ""
    for p in ("minimal", "earliest", "always"):
        s, n = timed(merge.coalesce(unary.apply_chain(r, [("past", Range(0, 30)), ("alwayspast", Range(0, 90))], p)).df)
        yield "merging", f"box over diamond, {p}", sf, s, n, ""


def joining(spark, sf):
    """Hash join on keys, bucketed join on time alone, and a nested loop over everything."""
    l = b.big(spark, sf).select(c1="cust", supp="supp")
    r = b.big(spark, sf).select(c2="cust", supp="supp")
    for name, make in (("hash", lambda: joins.temporal_join(l, r, ["supp"]).df), ("nested loop", lambda: baselines.nested_loop_join(l, r, ["supp"]))):
        s, n = timed(make())
        yield "joining", name, sf, s, n, ""


def averages(spark, sf):
    """Exponential average, load and query end to end, over the last 1, 10, 50 and 100 % of the days."""
    for percent in (1, 10, 50, 100):
        cut = int(2_499 * (1 - percent / 100))
        load = lambda spark, sf: (lambda s: s.with_df(s.df.where(F.col("t") >= cut)))(b.daily_revenue(spark, sf))  # noqa: E731, B023
        s, n = timed(ts.ema(load(spark, sf), 10).df)
        yield "averages", "fold", percent, s, n, ""
        s, n = timed(ts.ema_blocks(load(spark, sf), 10, 256).df)
        yield "averages", "block scan", percent, s, n, ""
        out, parts = baselines.window_ema(spark, sf, 10, load)
        yield "averages", "plain load and fold", percent, sum(parts.values()), out.count(), str({k: round(v, 2) for k, v in parts.items()})


FAMILIES = {f.__name__: f for f in (ownership, rivals, hierarchy, stations, generator, merging, joining, averages)}


def main() -> None:
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.config("spark.sql.session.timeZone", "UTC").getOrCreate()
    for name in sys.argv[2:] or FAMILIES:
        for row in FAMILIES[name](spark, sys.argv[1]):
            print(*(f"{x:.2f}" if isinstance(x, float) else x for x in row), sep=" | ", flush=True)


if __name__ == "__main__":
    main()
