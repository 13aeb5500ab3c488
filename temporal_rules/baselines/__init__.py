"""Methods to compare with: point-wise evaluation, indexed probing, plain window average, naive rounds."""

from __future__ import annotations

import time
from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.timeseries import Series, ema
from ..model import HI, LO, Range, TemporalRelation
from ..plans.runtime import Engine, Options


def pointwise(r: TemporalRelation, op: str, rng: Range) -> DataFrame:
    """An operator over closed ranges by expansion to cells: (keys, cell) where it holds."""
    rng, s = rng.on(r.timeline), r.timeline.scale
    cells = r.df.select(*r.keys, F.explode(F.sequence(LO, HI)).alias("cell")).distinct()
    a, b = s * rng.lo, s * rng.hi
    sign = 1 if op in ("past", "alwayspast") else -1
    moved = cells.withColumn("by", F.explode(F.sequence(F.lit(a), F.lit(b)))).select(*r.keys, (F.col("cell") + sign * F.col("by")).alias("cell"))
    if not op.startswith("always"):
        return moved.distinct()
    return moved.groupBy(*r.keys, "cell").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == b - a + 1).drop("n")


class GrowingIndex:
    """A source of (payload, lo, hi) rows that is scanned once, and an index over what was scanned so far."""

    def __init__(self, rows, key):
        self.rows, self.key, self.seen, self.scanned = iter(rows), key, defaultdict(list), 0

    def matches(self, k):
        """Rows with a key: first those in the index, then, as the scan goes on, those that it meets."""
        at = 0
        while True:
            found = self.seen[k]
            while at < len(found):
                yield found[at]
                at += 1
            if not self._scan_to(k):
                return

    def _scan_to(self, k) -> bool:
        for row in self.rows:
            self.scanned += 1
            mine = self.key(row[0])
            self.seen[mine].append(row)
            if mine == k:
                return True
        return False


def indexed_probe_join(left: list[tuple], right: list[tuple] | GrowingIndex, key_left, key_right=None):
    """Join of (payload, lo, hi) rows with an index that grows while the right side is scanned for the first time: a left
    row is answered from the index, and the scan goes on only when the consumer asks for more than that.  Single machine, small data."""
    index = right if isinstance(right, GrowingIndex) else GrowingIndex(right, key_right)
    for p, lo, hi in left:
        for q, a, b in index.matches(key_left(p)):
            if max(lo, a) <= min(hi, b):
                yield p, q, max(lo, a), min(hi, b)


def nested_loop_join(r: TemporalRelation, s: TemporalRelation, on: list[str]) -> DataFrame:
    """Every pair, then the filter: what indexing and hashing save."""
    l, q = r.df.alias("l"), s.df.alias("q")
    j = l.crossJoin(q).where((F.col(f"l.{LO}") <= F.col(f"q.{HI}")) & (F.col(f"q.{LO}") <= F.col(f"l.{HI}")))
    for k in on:
        j = j.where(F.col(f"l.{k}") == F.col(f"q.{k}"))
    return j.select(*(F.col(f"l.{k}") for k in r.keys), *(F.col(f"q.{k}") for k in s.keys if k not in r.keys), F.greatest(f"l.{LO}", f"q.{LO}").alias(LO), F.least(f"l.{HI}", f"q.{HI}").alias(HI))


def window_ema(spark, sf: str, n: int, load) -> tuple[DataFrame, dict[str, float]]:
    """Load and query end to end without rules, with the time of both."""
    t = time.time()
    s: Series = load(spark, sf)
    s = s.with_df(s.df.cache())
    s.df.count()
    loaded = time.time()
    out = ema(s, n).df
    out.count()
    return out, {"load_s": loaded - t, "query_s": time.time() - loaded}


def naive_fixpoint(program: str, facts: dict[str, TemporalRelation], predicate: str) -> TemporalRelation:
    """All rules, split into single operators and joins, over everything known in every round; nothing is kept between rounds."""
    return Engine(program, facts, Options(strategy="naive", fuse=False, canonical=True)).query(predicate)


def seminaive_fixpoint(program: str, facts: dict[str, TemporalRelation], predicate: str) -> TemporalRelation:
    """Rounds over what the last one added; all else of a rule is evaluated anew in each."""
    return Engine(program, facts, Options(fuse=False, static=False)).query(predicate)
