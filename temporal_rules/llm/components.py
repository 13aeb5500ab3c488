"""Connected components of a distributed edge list, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, staged


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of an edge; component is the least node reachable.

    Each round joins every node to the least node of its neighbourhood, first over larger
    neighbours, then over smaller ones; the frame of edges is staged in the shared folder, so
    neither lineage nor driver state grows.  A hub is only ever a key of an aggregate with
    map-side combining and of a join whose other side has one row for it.
    Null ends are ignored, repeated edges and self-loops do no harm, no edges give no rows.
    """
    now = staged(
        edges.select(F.greatest(a, b).cast("long").alias("u"), F.least(a, b).cast("long").alias("v")).where("u is not null and v is not null and u <> v").distinct(),
        "edges",
    )
    if now.isEmpty():
        return now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    nodes = now
    for _ in range(max_rounds):
        both = now.select("u", "v").unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        stars = (
            large.join(small, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
            .unionByName(small.select("u", F.col("m").alias("v")))
            .distinct()
        )
        nxt = staged(stars, "stars")
        tests = nxt.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("h"), F.countDistinct("u").alias("d")).first()
        tops = nxt.select(F.col("v").alias("u")).join(nxt, "u", "left_semi").limit(1).count()
        if now is not nodes:
            forget(now)
        now = nxt
        if tests["n"] == tests["d"] and not tops:
            break
    else:
        raise RuntimeError("components did not settle")
    found = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return found.unionByName(roots)
