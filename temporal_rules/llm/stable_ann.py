"""Approximate nearest neighbours by low-dimensional stable projections under a kd-tree.

Gaussian projection to ``m`` numbers turns a squared distance D into D x chi-square(m).  The
projected points are cut by a kd-tree; a search visits them by projected distance, verifies
true distances on the original vectors, and stops where a point as near as the k-th one found
would have been met before with probability ``confidence``.

The upper kd levels are fitted on a bounded sample (``sample_rows``) and deal all rows over
cells; each cell builds its own lower levels over all of its rows.  Every query is searched
first in its own cell, which bounds its k-th distance, and then in the cells that the stopping
test doesn't exclude.  Rows and queries of a cell meet in blocks of bounded size.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import maybe_broadcast, reach_workers, staged
from .vectors import matrix, sampled, usable, widths


def chi_square_quantile(p: float, m: int) -> float:
    """For even m, where the distribution is a finite sum."""
    if m % 2:
        raise ValueError("an even number of projections")
    lo, hi = 0.0, 50.0 + 10 * m
    for _ in range(200):
        mid = (lo + hi) / 2
        term, total = 1.0, 1.0
        for i in range(1, m // 2):
            term *= mid / 2 / i
            total += term
        lo, hi = (mid, hi) if 1 - math.exp(-mid / 2) * total < p else (lo, mid)
    return hi


@dataclass
class Cells:
    """Upper kd levels: split planes in heap order and the region of each cell."""

    projection: np.ndarray
    axis: np.ndarray
    value: np.ndarray
    low: np.ndarray
    high: np.ndarray

    @classmethod
    def fit(cls, sample: np.ndarray, m: int, levels: int, seed: int) -> "Cells":
        projection = np.random.default_rng(seed).standard_normal((sample.shape[1], m))
        points = sample @ projection
        axis, value = np.zeros((1 << levels) - 1, int), np.zeros((1 << levels) - 1)
        groups, low, high = [points], [np.full(m, -np.inf)], [np.full(m, np.inf)]
        at = 0
        for _ in range(levels):
            g2, l2, h2 = [], [], []
            for g, lo, hi in zip(groups, low, high):
                a = int(np.argmax(g.max(0) - g.min(0))) if len(g) else 0
                v = float(np.median(g[:, a])) if len(g) else 0.0
                axis[at], value[at] = a, v
                at += 1
                left, right = g[g[:, a] <= v], g[g[:, a] > v]
                hi1, lo1 = hi.copy(), lo.copy()
                hi1[a], lo1[a] = min(hi[a], v), max(lo[a], v)
                g2 += [left, right]
                l2 += [lo, lo1]
                h2 += [hi1, hi]
            groups, low, high = g2, l2, h2
        return cls(projection, axis, value, np.array(low), np.array(high))

    def project(self, x: np.ndarray) -> np.ndarray:
        return x @ self.projection

    def of(self, points: np.ndarray) -> np.ndarray:
        node = np.zeros(len(points), int)
        for _ in range(int(math.log2(len(self.low)))):
            node = 2 * node + 1 + (points[np.arange(len(points)), self.axis[node]] > self.value[node])
        return node - len(self.axis)

    def within(self, point: np.ndarray, squared: float) -> np.ndarray:
        gap = np.maximum(np.maximum(self.low - point, point - self.high), 0.0)
        return np.flatnonzero((gap * gap).sum(1) <= squared)


class LocalTree:
    """kd leaves over a block of projected points, searched nearest leaf first.  ``ids`` tell rows apart, ``keys`` are what is found."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, points: np.ndarray, leaf: int = 48, keys: np.ndarray | None = None):
        keys = ids if keys is None else keys
        stack, order, cuts = [np.arange(len(ids))], [], [0]
        while stack:
            g = stack.pop()
            if len(g) <= leaf:
                order.append(g)
                cuts.append(cuts[-1] + len(g))
                continue
            p = points[g]
            a = int(np.argmax(p.max(0) - p.min(0)))
            o = np.argsort(p[:, a], kind="stable")
            stack += [g[o[len(g) // 2 :]], g[o[: len(g) // 2]]]
        order = np.concatenate(order) if order else np.zeros(0, int)
        self.ids, self.keys, self.vectors, self.points = ids[order], keys[order], vectors[order], points[order]
        self.cuts = np.array(cuts)
        starts = self.cuts[:-1]
        self.low = np.minimum.reduceat(self.points, starts, axis=0)
        self.high = np.maximum.reduceat(self.points, starts, axis=0)

    def nearest(self, own: int, vector: np.ndarray, point: np.ndarray, k: int, ratio: float, bound: float) -> tuple[np.ndarray, np.ndarray]:
        """At most k (distance, id) found within ``bound``, and the search's stop by the chi-square test."""
        gap = np.maximum(np.maximum(self.low - point, point - self.high), 0.0)
        gap = (gap * gap).sum(1)
        order = np.argsort(gap, kind="stable")
        dist, ids = np.zeros(0), np.zeros(0, np.int64)
        at, step, best = 0, 1, bound
        while at < len(order) and gap[order[at]] <= ratio * best * best:
            leaves = order[at : at + step]
            rows = np.concatenate([np.arange(self.cuts[i], self.cuts[i + 1]) for i in leaves])
            near = self.points[rows] - point
            rows = rows[((near * near).sum(1) <= ratio * best * best) & (self.ids[rows] != own)]
            if len(rows):
                diff = self.vectors[rows] - vector
                d = np.sqrt((diff * diff).sum(1))
                dist, ids = np.concatenate([dist, d]), np.concatenate([ids, self.keys[rows]])
                keep = np.lexsort((ids, dist))[:k]
                dist, ids = dist[keep], ids[keep]
                if len(dist) == k:
                    best = min(best, dist[-1])
            at, step = at + step, min(2 * step, 16)
        ok = dist <= bound
        return dist[ok], ids[ok]


def nearest_neighbours(rows: DataFrame, queries: Column, k: int = 10, key: str = "vec_id", column: str = "embedding", m: int = 8, confidence: float = 0.98, sample_rows: int = 16_384, cell_rows: int = 8_192, query_rows: int = 4_096, max_cells: int = 4_096, seed: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest by Euclidean distance of every query row against all other rows.

    ``queries`` is a condition on ``rows``.  Null, zero and non-finite vectors and null keys take no part; vectors are
    compared with those of their width; equal distances go to the smaller key; every row that repeats a key is a
    query and a candidate of its own.  Fewer candidates than k give fewer rows; an empty table none.  Other columns are ignored.
    """
    spark = rows.sparkSession
    reach_workers(spark)
    good = rows.where(F.col(key).isNotNull() & usable(rows, column)).select(F.col(key).cast("long").alias("id"), F.col(column).alias("v"), F.coalesce(queries, F.lit(False)).alias("q"))
    parts = [_of_width(good.where(F.size("v") == w), w, k, m, confidence, sample_rows, cell_rows, query_rows, max_cells, seed) for w in widths(good, "v")]
    if not parts:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    return reduce(lambda a, b: a.unionByName(b), parts)


def _of_width(good: DataFrame, width: int, k: int, m: int, confidence: float, sample_rows: int, cell_rows: int, query_rows: int, max_cells: int, seed: int) -> DataFrame:
    """The search among vectors of one width."""
    spark = good.sparkSession
    n = good.count()
    levels = min(int(math.log2(max_cells)), max(0, math.ceil(math.log2(n / cell_rows))) if n > cell_rows else 0)
    cells = Cells.fit(sampled(good, "id", "v", width, sample_rows), m, levels, seed)
    ratio = chi_square_quantile(confidence, m)
    fitted = spark.sparkContext.broadcast(cells)  # at most max_cells regions and a width x m matrix
    kind = good.schema["v"].dataType.simpleString()

    def assign(batches):
        for batch in batches:
            cell = fitted.value.of(fitted.value.project(matrix(batch.column(1), width)))
            yield pa.record_batch([*batch.columns, pa.array(cell, pa.int64())], ["id", "v", "q", "row", "cell"])

    # Rows are numbered once, in the staged table, as keys may repeat.
    placed = staged(good.withColumn("row", F.monotonically_increasing_id()).mapInArrow(assign, f"id long, v {kind}, q boolean, row long, cell long"), "cells")
    sizes = {r["cell"]: r["n"] for r in placed.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}
    salts = {c: max(1, -(-x // (2 * cell_rows))) for c, x in sizes.items()}
    salt_of = spark.createDataFrame([(c, s) for c, s in salts.items()], "cell long, salts long")  # one row for each of at most max_cells cells
    blocks = placed.join(F.broadcast(salt_of), "cell").withColumn("salt", F.pmod(F.xxhash64("row"), F.col("salts")))
    asked = blocks.where("q").select(*(F.col(c).alias(f"q_{c}") for c in ("cell", "salt", "id", "row", "v")))

    def search(found, left, right):
        out_q, out_w, out_r, out_d = [], [], [], []
        if left.num_rows and right.num_rows:
            vectors = matrix(left.column("v"), width)
            tree = LocalTree(left.column("row").to_numpy(), vectors, fitted.value.project(vectors), keys=left.column("id").to_numpy())
            qv = matrix(right.column("q_v"), width)
            qp = fitted.value.project(qv)
            bounds = right.column("q_bound").to_numpy() if "q_bound" in right.column_names else np.full(len(qv), np.inf)
            for i, (own, asked_for) in enumerate(zip(right.column("q_row").to_pylist(), right.column("q_id").to_pylist())):
                d, ids = tree.nearest(own, qv[i], qp[i], k, ratio, bounds[i])
                out_q += [asked_for] * len(d)
                out_w += [own] * len(d)
                out_r += ids.tolist()
                out_d += d.tolist()
        return pa.table({"query_id": pa.array(out_q, pa.int64()), "row": pa.array(out_w, pa.int64()), "vec_id": pa.array(out_r, pa.int64()), "score": pa.array(out_d, pa.float64())})

    answer = "query_id long, row long, vec_id long, score double"
    # First the own block: an upper bound of the k-th distance, infinite where the block is too small.
    own = blocks.groupBy("cell", "salt").cogroup(asked.groupBy("q_cell", "q_salt")).applyInArrow(search, answer)
    bound = own.groupBy("row").agg(F.when(F.count(F.lit(1)) >= k, F.max("score")).otherwise(F.lit(float("inf"))).alias("bound"))
    known = staged(asked.join(bound, asked["q_row"] == bound["row"], "left").select(F.col("q_id").alias("id"), F.col("q_row").alias("row"), F.col("q_v").alias("v"), F.coalesce("bound", F.lit(float("inf"))).alias("bound")), "bounds")

    def spread(batches):
        for batch in batches:
            points = fitted.value.project(matrix(batch.column(2), width))
            limit = batch.column(3).to_numpy()
            hits = [fitted.value.within(p, ratio * b * b) for p, b in zip(points, limit)]
            take = np.repeat(np.arange(len(hits)), [len(h) for h in hits])
            got = batch.take(pa.array(take))
            yield pa.record_batch([*got.columns, pa.array(np.concatenate(hits) if hits else np.zeros(0, int), pa.int64())], ["id", "row", "v", "bound", "cell"])

    visits = known.mapInArrow(spread, f"id long, row long, v {kind}, bound double, cell long").join(F.broadcast(salt_of), "cell")
    visits = staged(visits.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1))).drop("salts"), "visits")
    # A block is copied once for every ``query_rows`` queries that visit it; one that none visits is not read again.
    asked_of = visits.groupBy("cell", "salt").agg(F.ceil(F.count(F.lit(1)) / query_rows).cast("long").alias("parts"))
    visits = visits.join(maybe_broadcast(asked_of), ["cell", "salt"]).withColumn("part", F.pmod(F.xxhash64("row"), F.col("parts")))
    spread_rows = blocks.select("cell", "salt", "id", "row", "v").join(maybe_broadcast(asked_of), ["cell", "salt"]).withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    by = ["cell", "salt", "part"]
    found = spread_rows.drop("parts").groupBy(*by).cogroup(visits.select(*(F.col(c).alias(f"q_{c}") for c in (*by, "id", "row", "v", "bound"))).groupBy(*(f"q_{c}" for c in by))).applyInArrow(search, answer)
    order = Window.partitionBy("row").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
