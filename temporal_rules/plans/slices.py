"""Recursion that does not move facts in time, solved slice by slice.

Where no operator stands between a predicate and itself, what holds in one stretch of time depends on nothing
outside it: the time axis is cut in slices of equal width, every slice runs all its rounds in one task, and
there is one exchange instead of one for each round.  Slices are counted first and only used where all are
small; else the rounds are distributed.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HI, LO, NEG, POS


@dataclass(frozen=True)
class Step:
    """One rule: which columns of the recursive literal and of the part are equal, and where the head's columns come from."""

    equal: tuple[tuple[int, str], ...]
    head: tuple[tuple[str, int | str], ...]  # ("known", column number) or ("part", column name)


@dataclass(frozen=True)
class Slicing:
    start: int
    width: int
    number: int

    def at(self, c: str):
        return F.least(F.lit(self.number - 1), F.greatest(F.lit(0), F.floor((F.greatest(F.col(c), F.lit(self.start)) - self.start) / self.width))).cast("int")

    def deal(self, df: DataFrame) -> DataFrame:
        """Facts cut at the slices' borders; the first slice begins and the last one ends nowhere."""
        x = df.withColumn("__slice", F.explode(F.sequence(self.at(LO), self.at(HI))))
        begin = F.col("__slice").cast("long") * self.width + self.start
        lo = F.when(F.col("__slice") == 0, F.col(LO)).otherwise(F.greatest(LO, begin))
        hi = F.when(F.col("__slice") == self.number - 1, F.col(HI)).otherwise(F.least(HI, begin + (self.width - 1)))
        return x.withColumns({LO: lo, HI: hi})


def slicing(tables: list[DataFrame], rows_each: int, most: int) -> Slicing | None:
    """Slices of about ``rows_each`` facts, no narrower than a quarter of the mean fact; None where facts would be copied
    over too many, or one slice would hold more than ``most``."""
    ends = reduce(lambda a, b: a.unionAll(b), [t.select(LO, HI) for t in tables])
    finite = (F.col(LO) > NEG) & (F.col(HI) < POS)
    s = ends.agg(
        F.count(F.lit(1)).alias("n"), F.sum((~finite).cast("long")).alias("endless"), F.avg(F.when(finite, F.col(HI) - F.col(LO) + 1)).alias("mean"),
        F.min(F.when(finite, F.col(LO))).alias("a"), F.max(F.when(finite, F.col(HI))).alias("b"),
    ).first()
    if s["a"] is None:
        return Slicing(0, 1, 1) if s["n"] <= most else None
    span = s["b"] - s["a"] + 1
    width = max(1, int(s["mean"] / 4), -(-span * rows_each // s["n"]))
    out = Slicing(s["a"], width, max(1, -(-span // width)))
    copies = s["endless"] * out.number + (s["n"] - s["endless"]) * (1 + s["mean"] / width)
    if copies > 8 * s["n"] + most:
        return None
    top = out.deal(ends).groupBy("__slice").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("n")).first()["n"]
    return out if top <= most else None


def solver(columns: list[str], steps: list[Step]):
    """A function from one slice's facts to what its rounds add, with the number of the round.

    Rows of kind 0 are the predicate's own, those of kind j + 1 the part of rule j.
    """
    chunk = 2_000_000  # pairs joined at once

    def codes(table: pa.Table, names: list[str]):
        """Columns as numbers from 1, 0 for null; equal values of one type have one number."""
        of, known = {}, {}
        for kind in {table.schema.field(n).type for n in names}:
            mine = [n for n in names if table.schema.field(n).type == kind]
            flat = pa.chunked_array([c for n in mine for c in table.column(n).chunks], kind).combine_chunks()
            flat = flat.chunk(0) if isinstance(flat, pa.ChunkedArray) else flat
            coded = flat.dictionary_encode()
            numbers = np.asarray(coded.indices.fill_null(-1)).astype(np.int64) + 1
            for i, n in enumerate(mine):
                of[n] = numbers[i * table.num_rows : (i + 1) * table.num_rows]
                known[n] = coded.dictionary
        return of, known

    def fresh(key, lo, hi, kkey, klo, khi):
        """Pieces of the first facts that the second ones don't cover, merged."""
        near = np.isin(kkey, key)
        kkey, klo, khi = kkey[near], klo[near], khi[near]
        n, m = len(key), len(kkey)
        who = np.concatenate([key, key, kkey, kkey])
        at = np.concatenate([lo, hi + 1, klo, khi + 1])
        new = np.concatenate([np.ones(n, np.int64), -np.ones(n, np.int64), np.zeros(2 * m, np.int64)])
        old = np.concatenate([np.zeros(2 * n, np.int64), np.ones(m, np.int64), -np.ones(m, np.int64)])
        order = np.lexsort((at, who))
        who, at = who[order], at[order]
        holds = (np.cumsum(new[order]) > 0) & (np.cumsum(old[order]) == 0)
        piece = np.flatnonzero(holds[:-1] & (who[1:] == who[:-1]) & (at[:-1] < at[1:]))
        if not len(piece):
            return who[:0], at[:0], at[:0]
        k, a, b = who[piece], at[piece], at[piece + 1] - 1
        start = np.concatenate([[True], (k[1:] != k[:-1]) | (a[1:] > b[:-1] + 1)])
        first = np.flatnonzero(start)
        return k[first], a[first], b[np.concatenate([first[1:], [len(k)]]) - 1]

    def solve(table: pa.Table) -> pa.Table:
        part_names = [[n for n in table.schema.names if n.startswith(f"p{j}_")] for j in range(len(steps))]
        of, known = codes(table, [*columns, *(n for p in part_names for n in p)])
        radix = max([1, *(int(v.max()) for v in of.values() if len(v))]) + 1
        kind = table.column("__kind").to_numpy()
        lo, hi = table.column("__lo").to_numpy(), table.column("__hi").to_numpy()

        def packed(cols):
            out = np.zeros(len(cols[0]) if cols else 0, np.int64)
            for c in cols:
                out = out * radix + c
            return out

        parts = []
        for j, s in enumerate(steps):
            rows = np.flatnonzero(kind == j + 1)
            join = packed([of[f"p{j}_{n}"][rows] for _, n in s.equal]) if s.equal else np.zeros(len(rows), np.int64)
            whole = np.ones(len(rows), bool)
            for _, n in s.equal:
                whole &= of[f"p{j}_{n}"][rows] > 0  # null equals nothing
            rows, join = rows[whole], join[whole]
            order = np.argsort(join, kind="stable")
            parts.append((rows[order], join[order]))
        none = np.zeros(0, np.int64)
        base = np.flatnonzero(kind == 0)
        own = packed([of[c][base] for c in columns]) if columns else np.zeros(len(base), np.int64)
        key, a, b = fresh(own, lo[base], hi[base], none, none, none)
        all_key, all_lo, all_hi = key, a, b
        found, turn = [(key, a, b, 0)], 0
        while len(key):
            turn += 1
            added = []
            for j, s in enumerate(steps):
                rows, join = parts[j]
                cols, left = [], key
                for _ in columns:
                    cols.append(left % radix)
                    left = left // radix
                cols.reverse()
                mine = packed([cols[i] for i, _ in s.equal]) if s.equal else np.zeros(len(key), np.int64)
                start, stop = np.searchsorted(join, mine), np.searchsorted(join, mine, side="right")
                for i, _ in s.equal:
                    stop = np.where(cols[i] > 0, stop, start)
                upto = np.cumsum(stop - start)
                at = 0
                while at < len(key):
                    end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + chunk, side="right")))
                    n = (stop - start)[at:end]
                    d = np.repeat(np.arange(at, end), n)
                    p = rows[np.repeat(start[at:end] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                    x, y = np.maximum(a[d], lo[p]), np.minimum(b[d], hi[p])
                    ok = x <= y
                    d, p = d[ok], p[ok]
                    got = packed([cols[c][d] if side == "known" else of[f"p{j}_{c}"][p] for side, c in s.head]) if s.head else np.zeros(len(d), np.int64)
                    if len(got):
                        new = fresh(got, x[ok], y[ok], all_key, all_lo, all_hi)
                        all_key, all_lo, all_hi = (np.concatenate(z) for z in zip((all_key, all_lo, all_hi), new))
                        added.append(new)
                    at = end
            key, a, b = (np.concatenate(z) for z in zip(*added)) if added else (none, none, none)
            found.append((key, a, b, turn))
        keys = np.concatenate([f[0] for f in found])
        out = {}
        for c in reversed(columns):
            number, keys = keys % radix, keys // radix
            out[c] = known[c].take(pa.array(number - 1, mask=number == 0))
        out = {c: out[c] for c in columns}
        out |= {"__lo": pa.array(np.concatenate([f[1] for f in found])), "__hi": pa.array(np.concatenate([f[2] for f in found]))}
        out["__turn"] = pa.array(np.concatenate([np.full(len(f[0]), f[3], np.int32) for f in found]), pa.int32())
        return pa.table(out)

    return solve


def solve_slices(base: DataFrame, parts: list[DataFrame], columns: list[str], steps: list[Step], cut: Slicing) -> DataFrame:
    """(columns, __lo, __hi, __turn) of everything the recursion gives, in pieces of slices and rounds."""
    frames = [cut.deal(base.select(*columns, LO, HI)).withColumn("__kind", F.lit(0))]
    for j, p in enumerate(parts):
        named = p.select(*(F.col(c).alias(f"p{j}_{c}") for c in p.columns if c not in (LO, HI)), LO, HI)
        frames.append(cut.deal(named).withColumn("__kind", F.lit(j + 1)))
    whole = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), frames)
    schema = "".join(f"`{c}` {base.schema[c].dataType.simpleString()}, " for c in columns) + f"{LO} long, {HI} long, __turn int"
    return whole.groupBy("__slice").applyInArrow(solver(columns, steps), schema)
