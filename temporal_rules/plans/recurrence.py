"""Recursion whose value is a linear function of the value an instant before: series that rules generate, and
averages that rules carry on.

    day(Y)     :- past[1,1] day(X), Y = X + 1.
    part(Y)    :- past[1,1] ema(X), Y = X * 9 / 11.
    part(Y)    :- stock(V), Y = V * 2 / 11.
    ema(Y)     :- part(X), Y = sum(X).

The first kind never ends: it is a pattern whose value moves from one occurrence to the next.  The second is one
ordered fold for each series instead of a round for each instant.
"""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import HI, LO, TemporalRelation
from ..staging import staged
from .language import Aggregate, Assign, Program, Rule, Var


def linear_form(spark: SparkSession, c: Assign) -> tuple[str, float, float] | None:
    """(variable, a, b) of an assignment a x + b; None if it is anything else."""
    if len(c.variables) != 1:
        return None
    name = next(iter(c.variables))
    at = [0.0, 1.0, 2.0, -3.5]
    try:
        y = [spark.range(1).select(F.lit(x).cast("double").alias(name)).select(F.expr(c.expression).cast("double").alias("y")).first()["y"] for x in at]
    except Exception:  # not an expression over numbers
        return None
    if any(v is None for v in y):
        return None
    a, b = y[1] - y[0], y[0]
    close = all(abs(v - (a * x + b)) <= 1e-9 * max(1.0, abs(v)) for x, v in zip(at, y))
    return (name, a, b) if close else None


def _moved(rule: Rule, inside: set[str]) -> tuple[str, int, int, Assign] | None:
    """p(K, Y) :- past[d,d] q(K, X), Y = f(X): the predicate read, d, the place of Y, the assignment."""
    if len(rule.literals) != 1 or len(rule.conditions) != 1 or not isinstance(rule.conditions[0], Assign) or not rule.head or rule.head.span:
        return None
    x, c = rule.literals[0], rule.conditions[0]
    if x.binary or x.negated or x.atom.span or x.atom.predicate not in inside or len(x.ops) != 1 or x.ops[0][0] != "past":
        return None
    rng = x.ops[0][1]
    if rng.lo != rng.hi or rng.lo < 1 or len(rule.head.terms) != len(x.atom.terms) or len(c.variables) != 1:
        return None
    value = Var(next(iter(c.variables)))
    spots = [i for i, (h, t) in enumerate(zip(rule.head.terms, x.atom.terms)) if h != t]
    names = [t for t in x.atom.terms if isinstance(t, Var)]
    if len(spots) != 1 or rule.head.terms[spots[0]] != Var(c.name) or x.atom.terms[spots[0]] != value or len(set(names)) != len(x.atom.terms):
        return None
    return x.atom.predicate, rng.lo, spots[0], c


@dataclass(frozen=True)
class Stepping:
    """p(K, f(X)) an exact time after p(K, X)."""

    predicate: str
    rule: Rule
    by: int
    place: int
    a: float
    b: float


@dataclass(frozen=True)
class Carried:
    """total(K, sum) of inputs, one of which is a total some instants ago times a, plus b."""

    total: str
    part: str
    feed: Rule
    gather: Rule
    by: int
    place: int
    a: float
    b: float


def recognise_recurrence(spark: SparkSession, program: Program, group: list[str]) -> Stepping | Carried | None:
    inside = set(group)
    rules = [r for p in group for r in program.for_head(p)]
    loops = [r for r in rules if any(a.predicate in inside for x in r.literals for a in x.atoms())]
    if len(group) == 1 and len(loops) == 1 and (m := _moved(loops[0], inside)) and (f := linear_form(spark, m[3])):
        return Stepping(group[0], loops[0], m[1], m[2], f[1], f[2])
    if len(group) != 2 or len(loops) != 2:
        return None
    feeds = [(r, m) for r in loops if (m := _moved(r, inside))]
    sums = [r for r in loops if len(r.conditions) == 1 and isinstance(r.conditions[0], Aggregate) and r.conditions[0].function == "sum"]
    if len(feeds) != 1 or len(sums) != 1:
        return None
    (feed, (total, by, place, c)), gather = feeds[0], sums[0]
    part, agg, x = feed.head.predicate, gather.conditions[0], gather.literals[0]
    if total == part or gather.head.predicate != total or len(gather.literals) != 1 or x.ops or x.negated or x.binary or x.atom.predicate != part or gather.head.span or x.atom.span:
        return None
    if [t for i, t in enumerate(x.atom.terms) if i != place] != [t for i, t in enumerate(gather.head.terms) if i != place]:
        return None
    if x.atom.terms[place] != Var(agg.value) or gather.head.terms[place] != Var(agg.name):
        return None
    f = linear_form(spark, c)
    return Carried(total, part, feed, gather, by, place, f[1], f[2]) if f else None


def carry_on(inputs: DataFrame, seeds: DataFrame | None, keys: list[str], value: str, c: Carried, step: int) -> tuple[DataFrame, DataFrame]:
    """(keys, value, __at) of the totals of punctual inputs up to the last one of a series, and the last ones.

    ``inputs`` and ``seeds`` have keys, value and __at (a cell); a seed stands for the sum where it is.  Instants
    without input carry the total on, and after the last one it goes on for ever: that is a pattern.
    Rows stream by in order of time with one number of state for each series.
    """
    rows = inputs.groupBy(*keys, "__at").agg(F.sum(value).alias("__b"), F.lit(None).cast("double").alias("__seed"))
    if seeds is not None:
        given = seeds.groupBy(*keys, "__at").agg(F.lit(None).cast("double").alias("__b"), F.max(value).alias("__seed"))
        rows = rows.unionByName(given).groupBy(*keys, "__at").agg(F.max("__b").alias("__b"), F.max("__seed").alias("__seed"))
    rows = rows.withColumn("__r", F.pmod("__at", F.lit(step)))
    names = [*keys, "__r"]

    def ahead(y: float, n: int) -> float:
        if n == 1:
            return c.a * y + c.b
        return y + n * c.b if c.a == 1 else c.a**n * y + c.b * (c.a**n - 1) / (c.a - 1)

    def fold(batches):
        last, at, y = None, None, 0.0
        for batch in batches:
            out = []
            cols = [[repr(v) for v in batch.column(k).to_pylist()] for k in names]
            for name, t, b, seed in zip(zip(*cols), batch.column("__at").to_pylist(), batch.column("__b").to_pylist(), batch.column("__seed").to_pylist()):
                before = ahead(y, (t - at) // step) if name == last else 0.0
                y = seed if seed is not None else (b or 0.0) + before
                last, at = name, t
                out.append(y)
            yield pa.record_batch([*(batch.column(k) for k in names), pa.array(out, pa.float64()), batch.column("__at")], [*names, value, "__at"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*names).schema), f"`{value}` double, __at long"])
    folded = rows.repartition(*names).sortWithinPartitions(*names, "__at").mapInArrow(fold, schema)
    after = F.lead("__at").over(Window.partitionBy(*names).orderBy("__at"))
    folded = staged(folded.withColumn("__after", after), "carried")
    x = folded.withColumn("__x", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce((F.col("__after") - F.col("__at")) / step - 1, F.lit(0)).cast("long"))))
    n = F.col("__x").cast("double")
    power = F.pow(F.lit(c.a), n)
    carried = F.col(value) + n * c.b if c.a == 1 else F.col(value) * power + F.lit(c.b) * (power - 1) / F.lit(c.a - 1)
    whole = x.select(*keys, F.when(F.col("__x") == 0, F.col(value)).otherwise(carried).alias(value), (F.col("__at") + F.col("__x") * step).alias("__at"))
    return whole, folded.where("__after is null").select(*keys, value, "__at")


def punctual(r: TemporalRelation) -> bool:
    return r.df.where(F.col(LO) != F.col(HI)).isEmpty()
