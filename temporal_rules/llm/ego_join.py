"""Similarity join of vectors by epsilon grid order.

cos >= t between unit vectors is a Euclidean distance of at most eps = sqrt(2 - 2t).  Vectors
are rotated to leading principal axes (fitted on a bounded sample; any rotation is right, a
good one skips more) and sorted by their grid cells of width eps.  The sequence is cut in
intervals, intervals are joined recursively, and a pair of intervals whose boxes are more
than eps apart is skipped.  What remains is compared by matrix products: single precision
with a margin decides clear cases, double precision the others.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, reach_workers, staged
from .components import components
from .vectors import matrix, sampled, usable, widths

MARGIN = 1e-4  # far above the rounding of a single-precision product of unit vectors


def unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def principal_axes(sample: np.ndarray, m: int) -> np.ndarray:
    width = sample.shape[1]
    m = min(m, width)
    if len(sample) < 2:
        return np.eye(width)[:, :m]
    values, axes = np.linalg.eigh(np.cov(sample.T).reshape(width, width))
    return axes[:, np.argsort(-values)[:m]]


class Intervals:
    """A sequence of boxes under a binary tree of their unions."""

    def __init__(self, low: np.ndarray, high: np.ndarray):
        self.levels = [(low, high)]
        while len(low) > 1:
            odd = len(low) % 2
            cut = lambda x, f, fill: f(np.concatenate([x, np.full((odd, x.shape[1]), fill)]).reshape(-1, 2, x.shape[1]), axis=1)
            low, high = cut(low, np.min, np.inf), cut(high, np.max, -np.inf)
            self.levels.append((low, high))

    def near(self, low: np.ndarray, high: np.ndarray, eps: float) -> np.ndarray:
        """Numbers of the boxes within eps of one box, by descent through the unions."""
        at = np.array([0])
        for lo, hi in reversed(self.levels):
            at = at[at < len(lo)]
            gap = np.maximum(np.maximum(lo[at] - high, low - hi[at]), 0.0)
            at = at[(gap * gap).sum(axis=1) <= eps * eps]
            if lo is not self.levels[0][0]:
                at = np.stack([2 * at, 2 * at + 1], axis=1).ravel()
        return at


def boxes(points: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    starts = np.arange(0, len(points), rows)
    return starts, np.minimum.reduceat(points, starts, axis=0), np.maximum.reduceat(points, starts, axis=0)


def join_intervals(x: np.ndarray, y: np.ndarray | None, times_x: np.ndarray, times_y: np.ndarray, axes: np.ndarray, t: float, leaf: int = 256):
    """Links between two sequences of unit vectors (y None: within one).

    Returns for every vector the number of rows linked with it, and links that span the
    components.  ``times`` are the numbers of rows that share each vector.
    """
    eps = math.sqrt(max(0.0, 2 - 2 * t)) + 1e-9
    same = y is None
    y = x if same else y
    px, py = x @ axes, y @ axes
    sx, lx, hx = boxes(px, leaf)
    sy, ly, hy = boxes(py, leaf)
    tree = Intervals(ly, hy)
    x32, y32 = x.astype(np.float32), y.astype(np.float32)
    nx, ny = np.zeros(len(x), np.int64), np.zeros(len(y), np.int64)
    label = np.arange(len(x) if same else len(x) + len(y))
    shift = 0 if same else len(x)
    links: list[tuple[int, int]] = []
    for b, start in enumerate(sx):
        near = tree.near(lx[b], hx[b], eps)
        if same:
            near = near[near >= b]
        if not len(near):
            continue
        rows = np.arange(start, min(start + leaf, len(x)))
        for lo in range(0, len(near), 16):
            cols = np.concatenate([np.arange(sy[j], min(sy[j] + leaf, len(y))) for j in near[lo : lo + 16]])
            product = x32[rows] @ y32[cols].T
            i, j = np.nonzero(product >= t - MARGIN)
            clear = product[i, j] >= t + MARGIN
            i, j = rows[i], cols[j]
            if not clear.all():
                unsure = np.flatnonzero(~clear)
                clear[unsure] = (x[i[unsure]] * y[j[unsure]]).sum(axis=1) >= t
                i, j = i[clear], j[clear]
            if same:
                i, j = i[i < j], j[i < j]
            if not len(i):
                continue
            nx += np.bincount(i, weights=times_y[j], minlength=len(x)).astype(np.int64)
            ny += np.bincount(j, weights=times_x[i], minlength=len(y)).astype(np.int64)
            while True:
                a, c = label[i], label[j + shift]
                apart = a != c
                if not apart.any():
                    break
                i, j, a, c = i[apart], j[apart], a[apart], c[apart]
                _, first = np.unique(np.maximum(a, c), return_index=True)
                for f in first:
                    links.append((int(i[f]), int(j[f])))
                    p, q = label[i[f]], label[j[f] + shift]
                    if p != q:
                        label[label == max(p, q)] = min(p, q)
    return (nx + ny if same else nx), (None if same else ny), links


def similar_vectors(rows: DataFrame, t: float = 0.95, key: str = "vec_id", column: str = "embedding", m: int = 8, sample_rows: int = 8_192, interval: int = 8_192, most_intervals: int = 100_000) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row.

    Rows link if the cosine of their vectors is at least t.  Rows with one and the same vector
    are compared once; each is linked with the others.  Null, zero and non-finite vectors
    and null keys link with nothing, vectors with those of their own width only; a null key has a null
    component.  An empty table gives no rows; other columns are ignored.
    """
    base = rows.select(F.col(key).cast("long").alias("id"), F.col(column).alias("v"))
    found = widths(base.where(F.col("id").isNotNull() & usable(base, "v")), "v")
    size = F.coalesce(F.size("v"), F.lit(0))
    if len(found) > 1:
        parts = [base.where(size == w) for w in found] + [base.where(~size.isin(found))]
        return reduce(lambda a, b: a.unionByName(b), [similar_vectors(p, t, "id", "v", m, sample_rows, interval, most_intervals) for p in parts])
    spark = rows.sparkSession
    reach_workers(spark)
    good = base.where(F.col("id").isNotNull() & usable(base, "v"))
    width = found[0] if found else 0
    alone = lambda df: df.select(F.col("id").alias("vec_id"), F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"), F.lit(True).alias("kept"))
    if not width:
        return alone(base)
    fits = usable(base, "v") & F.col("id").isNotNull() & (F.coalesce(F.size("v"), F.lit(0)) == width)
    classes = staged(good.where(F.size("v") == width).groupBy("v").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("times")), "classes")
    n = classes.count()
    interval = max(interval, -(-n // most_intervals))
    axes = principal_axes(unit(sampled(classes, "rep", "v", width, sample_rows)), m)
    eps = math.sqrt(2 - 2 * t)
    m = axes.shape[1]
    kind = classes.schema["v"].dataType.simpleString()
    known = spark.sparkContext.broadcast(axes)

    def grid(batches):
        for batch in batches:
            cells = np.floor(unit(matrix(batch.column(0), width)) @ known.value / eps).astype(np.int32)
            yield pa.record_batch([*batch.columns, *(pa.array(cells[:, c]) for c in range(m))], ["v", "rep", "times", *(f"g{c}" for c in range(m))])

    cells = staged(classes.mapInArrow(grid, f"v {kind}, rep long, times long, " + ", ".join(f"g{c} int" for c in range(m))), "grid")
    order = [*(f"g{c}" for c in range(m)), "rep"]
    parts = max(1, -(-n // interval))

    def cut(batches):
        from pyspark import TaskContext

        first = TaskContext.get().partitionId() << 32
        at = 0
        for batch in batches:
            number = first + (at + np.arange(batch.num_rows)) // interval
            at += batch.num_rows
            yield pa.record_batch([batch.column(0), batch.column(1), batch.column(2), pa.array(number, pa.int64()), pa.array(at - batch.num_rows + np.arange(batch.num_rows), pa.int64())], ["v", "rep", "times", "interval", "place"])

    sequence = staged(cells.repartitionByRange(parts, *order).sortWithinPartitions(*order).mapInArrow(cut, f"v {kind}, rep long, times long, interval long, place long"), "sequence")
    forget(cells)

    def corner(group):
        p = unit(matrix(group.column("v"), width)) @ known.value
        return pa.table({"interval": group.column("interval").slice(0, 1), "n": pa.array([group.num_rows], pa.int64()), "low": pa.array([p.min(0).tolist()], pa.list_(pa.float64())), "high": pa.array([p.max(0).tolist()], pa.list_(pa.float64()))})

    # One box for each interval, at most ``most_intervals`` of them whatever the number of rows.
    found = sorted(sequence.groupBy("interval").applyInArrow(corner, "interval long, n long, low array<double>, high array<double>").collect(), key=lambda r: r["interval"])
    if not found:
        return alone(base)
    # Neighbours in the sequence are joined up to the wanted size, however many partitions the sort had.
    group_of, sizes = [], []
    for r in found:
        if not sizes or sizes[-1] + r["n"] > interval:
            sizes.append(0)
        sizes[-1] += r["n"]
        group_of.append(len(sizes) - 1)
    number = list(range(len(sizes)))
    cuts = np.searchsorted(group_of, number)
    low = np.minimum.reduceat(np.array([r["low"] for r in found]), cuts, axis=0)
    high = np.maximum.reduceat(np.array([r["high"] for r in found]), cuts, axis=0)
    joined = spark.createDataFrame([(r["interval"], g) for r, g in zip(found, group_of)], "interval long, number long")
    ordered = sequence.join(F.broadcast(joined), "interval")  # one row for each interval of the sort
    shared = spark.sparkContext.broadcast((number, low, high))

    def partners(batches):
        number, low, high = shared.value
        tree = Intervals(low, high)
        for batch in batches:
            for at in batch.column(0).to_pylist():
                near = tree.near(low[at], high[at], eps + 1e-9)
                near = near[near >= at]
                yield pa.record_batch([pa.array([number[at]] * len(near), pa.int64()), pa.array([number[j] for j in near], pa.int64())], ["i", "j"])

    pairs = staged(spark.range(0, len(number), 1, min(len(number), 200)).mapInArrow(partners, "i long, j long"), "pairs")
    left = pairs.join(ordered, F.col("i") == F.col("number")).select("i", "j", "v", "rep", "times", "interval", "place", F.lit(0).alias("side"))
    right = pairs.where("i <> j").join(ordered, F.col("j") == F.col("number")).select("i", "j", "v", "rep", "times", "interval", "place", F.lit(1).alias("side"))

    def compare(group):
        side = group.column("side").to_numpy()
        run, place, rep, times = (group.column(c).to_numpy() for c in ("interval", "place", "rep", "times"))
        vectors = unit(matrix(group.column("v"), width))
        pick = [np.flatnonzero(side == s) for s in (0, 1)]
        pick = [p[np.lexsort((place[p], run[p]))] for p in pick]
        a, b = pick
        if len(b):
            na, nb, links = join_intervals(vectors[a], vectors[b], times[a], times[b], known.value, t)
            ids, counts, ends = np.concatenate([rep[a], rep[b]]), np.concatenate([na, nb]), [(rep[a][i], rep[b][j]) for i, j in links]
        elif group.column("i")[0] == group.column("j")[0]:
            counts, _, links = join_intervals(vectors[a], None, times[a], times[a], known.value, t)
            ids, ends = rep[a], [(rep[a][i], rep[a][j]) for i, j in links]
        else:
            ids, counts, ends = np.zeros(0, np.int64), np.zeros(0, np.int64), []
        ids, counts = ids[counts > 0], counts[counts > 0]
        return pa.table({
            "a": pa.array([*ids.tolist(), *(int(x) for x, _ in ends)], pa.int64()),
            "b": pa.array([None] * len(ids) + [int(y) for _, y in ends], pa.int64()),
            "n": pa.array([*counts.tolist(), *[None] * len(ends)], pa.int64()),
        })

    got = staged(left.unionByName(right).groupBy("i", "j").applyInArrow(compare, "a long, b long, n long"), "links")
    forget(sequence)
    parts_of = components(got.where("b is not null").select("a", "b"))
    counts = got.where("n is not null").groupBy("a").agg(F.sum("n").alias("n"))
    facts = classes.join(counts, F.col("rep") == F.col("a"), "left").join(parts_of, F.col("rep") == F.col("node"), "left")
    facts = facts.select("v", (F.coalesce("n", F.lit(0)) + F.col("times") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    linked = base.where(fits).join(facts, "v").select(F.col("id").alias("vec_id"), "n_links", "component_id", (F.col("id") == F.col("component_id")).alias("kept"))
    return linked.unionByName(alone(base.where(~fits)))
