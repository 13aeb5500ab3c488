"""Near-duplicate documents: fast similarity sketches, banding, exact verification, components.

1. Every text becomes its set of five-word shingles, a sketch of ``size`` coordinates and
   size / rows band keys.  Texts with equal sets are one class, represented by its least doc_id.
2. A band's bucket first compares all members with its least one, on full sets; the links
   found join most of a group of copies with one comparison for each.
3. Buckets that still hold several components compare the members of different components, in
   blocks of bounded size; a pair is compared in the first band that it shares, and goes on
   to full sets if its sketches agree in ``screen`` of their coordinates (a pair at the
   threshold agrees in less with probability below 1e-5).
No bucket is capped and no pair list is built: what a block returns are the links of a forest.
A pair at 75 % shares none of 32 bands of 4 with probability 5e-6.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, maybe_broadcast, reach_workers, staged
from .components import components
from .shingles import bands, jaccard_parts, shingle_hashes, sketch

def signatures(docs: DataFrame, width: int, size: int, rows: int) -> DataFrame:
    """doc_id, n (set size), k1, k2 (a 128-bit hash of the set), bands."""
    reach_workers(docs.sparkSession)

    def sign(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                sets = [shingle_hashes(t, width) for t in part.column(1).to_pylist()]
                keys = bands(sketch(sets, size), rows)
                n = np.array([len(s) for s in sets], np.int64)
                k1 = np.array([int(np.add.reduce(s * np.uint64(0x9E3779B97F4A7C15) ^ (s >> np.uint64(29)), dtype=np.uint64)) for s in sets], np.uint64).view(np.int64)
                k2 = np.array([int(np.bitwise_xor.reduce(s)) if len(s) else 0 for s in sets], np.uint64).view(np.int64)
                flat = pa.array(keys.view(np.int64).ravel())
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, keys.shape[1], dtype=np.int32)), flat)
                yield pa.record_batch([part.column(0), pa.array(n), pa.array(k1), pa.array(k2), lists], ["doc_id", "n", "k1", "k2", "bands"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(sign, "doc_id long, n long, k1 long, k2 long, bands array<long>")


def _star_links(stars: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """Links among (doc_id, leader) pairs, verified on full sets; a busy leader's members are dealt over salts."""
    busy = stars.groupBy("leader").agg(F.ceil(F.count(F.lit(1)) / 256).alias("salts"))
    dealt = stars.join(busy, "leader").withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.col("salts")))
    member = dealt.join(texts, "doc_id").select("leader", "salt", "doc_id", "text", F.lit(False).alias("is_leader"))
    lead = dealt.select("leader", "salt").distinct().join(texts, F.col("leader") == texts["doc_id"]).select("leader", "salt", "doc_id", "text", F.lit(True).alias("is_leader"))

    def verify(key, group):
        is_leader = group.column("is_leader").to_pylist()
        ids, text = group.column("doc_id").to_pylist(), group.column("text")
        heads = [shingle_hashes(text[i].as_py(), width) for i, x in enumerate(is_leader) if x]
        out = []
        for i, x in enumerate(is_leader):
            if not x:
                mine = shingle_hashes(text[i].as_py(), width)
                for head in heads:
                    both, union = jaccard_parts(mine, head)
                    if 100 * both >= percent * union:
                        out.append(ids[i])
                        break
        return pa.table({"a": pa.array(out, pa.int64()), "b": pa.array([key[0].as_py()] * len(out), pa.int64())})

    return member.unionByName(lead).groupBy("leader", "salt").applyInArrow(verify, "a long, b long")


def block_links(key: int, ids: list[int], part: np.ndarray, side: np.ndarray, sets: list[np.ndarray], size: int, rows: int, screen: float, percent: int) -> list[tuple[int, int]]:
    """Links that join different components within one block of a bucket.

    ``part`` numbers the components that are known, ``side`` is 0 or 1 for the two halves of
    a pair of blocks (all 2 within one block).  Pairs joined already are not compared.
    """
    sk = sketch(sets, size)
    keys = bands(sk, rows)
    up = {int(p): int(p) for p in part}

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    out = []
    key = np.uint64(key & (2**64 - 1))
    for i in np.argsort([len(s) for s in sets], kind="stable"):
        mine = root(int(part[i]))
        roots = np.array([root(int(p)) for p in part])
        other = np.flatnonzero((roots != mine) & ((side != side[i]) | (side == 2)))
        if not len(other):
            continue
        agree = (sk[other] == sk[i]).mean(axis=1)
        other = other[agree >= screen]
        if not len(other):
            continue
        same = keys[other] == keys[i]
        first = same.argmax(axis=1)
        other = other[keys[i][first] == key]
        if not len(other):
            continue
        lengths = np.array([len(sets[j]) for j in other])
        everything = np.concatenate([sets[j] for j in other])
        spot = np.minimum(np.searchsorted(sets[i], everything), len(sets[i]) - 1)
        both = np.add.reduceat((sets[i][spot] == everything).astype(np.int64), np.cumsum(lengths) - lengths)
        linked = other[100 * both >= percent * (len(sets[i]) + lengths - both)]
        for j in linked:
            a, b = root(int(part[i])), root(int(part[j]))
            if a != b:
                up[max(a, b)] = min(a, b)
                out.append((ids[i], ids[j]))
    return out


def _cross_links(rest: DataFrame, texts: DataFrame, width: int, size: int, rows: int, screen: float, percent: int) -> DataFrame:
    """Links between components that share a bucket: (key, doc_id, c, blocks) compared block against block."""
    dealt = rest.withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks"))).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    dealt = dealt.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "doc_id", "c").join(texts, "doc_id")

    def compare(key, group):
        i, j = key[1].as_py(), key[2].as_py()
        side = np.full(group.num_rows, 2) if i == j else (group.column("block").to_numpy() == j).astype(int)
        part = group.column("c").to_numpy()
        ids = group.column("doc_id").to_pylist()
        sets = [shingle_hashes(t.as_py(), width) for t in group.column("text")]
        links = block_links(key[0].as_py(), ids, part, side, sets, size, rows, screen, percent)
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return dealt.groupBy("key", "i", "j").applyInArrow(compare, "a long, b long")


def near_duplicates(docs: DataFrame, percent: int = 75, width: int = 5, size: int = 128, rows: int = 4, screen: float = 0.58) -> DataFrame:
    """One row for each row of docs: doc_id, n_shingles, component_id, kept.

    Documents link if 100 * |intersection| >= percent * |union| of their shingle sets; a text
    of fewer words than ``width`` is one shingle; null, empty and blank texts have none and
    stay alone.  Rows that repeat a doc_id are one node; a null doc_id takes no part, has a
    null component and is kept.  Columns other than doc_id and text are ignored; an empty table gives no rows.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sig = staged(signatures(texts, width, size, rows), "signatures")
    nodes = sig.where("n > 0 and doc_id is not null")
    classes = nodes.groupBy("k1", "k2", "n").agg(F.min("doc_id").alias("doc_id"))
    reps = nodes.join(classes, ["k1", "k2", "n", "doc_id"], "left_semi")
    keyed = reps.select("doc_id", "n", F.explode("bands").alias("key"))
    heads = staged(keyed.groupBy("key").agg(F.min("doc_id").alias("leader"), F.count(F.lit(1)).alias("members"), F.sum("n").alias("shingles")).where("members > 1"), "heads")
    members = staged(keyed.drop("n").join(maybe_broadcast(heads), "key"), "members")
    ids = maybe_broadcast(members.select("doc_id").distinct())
    wanted = staged(texts.join(ids, "doc_id", "left_semi").distinct(), "texts")
    stars = members.where("doc_id <> leader").select("doc_id", "leader").distinct()
    links = staged(_star_links(stars, wanted, width, percent), "links")
    first = components(links)
    joined = members.join(first, members["doc_id"] == first["node"], "left").select("key", "doc_id", "members", "shingles", F.coalesce("component", "doc_id").alias("c"))
    joined = staged(joined, "joined")
    mixed = joined.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("key")
    # Blocks of at most about 1,024 texts and 2,000,000 shingles; one very long text makes one block more, not all of them small.
    blocks = F.greatest(F.ceil(F.col("members") / 1024), F.ceil(F.col("shingles") / 2_000_000))
    rest = joined.join(maybe_broadcast(mixed), "key", "left_semi").withColumn("blocks", blocks)
    more = staged(_cross_links(rest, wanted, width, size, rows, screen, percent), "links")
    found = staged(components(links.unionByName(more)), "components")
    for used in (heads, members, joined, wanted, links, more):
        forget(used)
    c = classes.withColumnRenamed("doc_id", "rep").join(found, F.col("rep") == found["node"], "left").select("k1", "k2", "n", F.coalesce("component", "rep").alias("component"))
    out = sig.drop("bands").join(c, ["k1", "k2", "n"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def one_of_each(docs: DataFrame, **how) -> DataFrame:
    """The rows of docs, all columns as they are, with one document left of each near-duplicate component.

    The document with the least doc_id stays; of rows that repeat a doc_id one stays; rows
    without a doc_id all stay, and so do null and empty texts, which are near nothing.  Very long texts are compared whole.
    An empty table gives no rows; other columns may have any names.
    """
    found = near_duplicates(docs, **how)
    gone = found.where(~F.col("kept")).select("doc_id").distinct()
    out = docs.join(maybe_broadcast(gone), "doc_id", "left_anti").select(docs.columns)
    again = docs.where("doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id")
    if again.isEmpty():
        return out
    once = out.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(docs.columns)
    return out.join(again, "doc_id", "left_anti").select(docs.columns).unionByName(once)
