"""Mixing sources to target weights by a low-discrepancy schedule over equal-word blocks.

Slot i of the schedule belongs to the source in whose share of [0, 1) the point
frac(i x golden ratio) falls.  The r-th slot of a source takes the r-th block of the source's
shuffled stream of words, which starts again after its last word, until the source's target
is met; slots beyond it are skipped and what the points left open at the end is appended.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import numbered, reach_workers, staged, words_of

GOLDEN = 0x9E3779B97F4A7C15


def targets(sizes: dict[str | None, int], weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> dict[str | None, float]:
    """Words wanted from each source: ``share`` of all words by weight, at most ``most`` times the source's size.

    Weights repeat over the sources by code point, null last.  What a full source can't take
    is shared again by weight among the others, until none is above its limit.
    """
    names = sorted((s for s in sizes if s is not None)) + [s for s in sizes if s is None]
    weight = {s: float(weights[i % len(weights)]) for i, s in enumerate(names)}
    total, out, free = share * sum(sizes.values()), {}, list(names)
    while free:
        rest = total - sum(out.values())
        unit = sum(weight[s] for s in free)
        full = [s for s in free if rest * weight[s] / unit > most * sizes[s]]
        if not full:
            out.update({s: rest * weight[s] / unit for s in free})
            break
        out.update({s: most * sizes[s] for s in full})
        free = [s for s in free if s not in full]
    return out


def block_words(total: float, least_slots: int = 65_536, most_words: int = 4096) -> int:
    return max(1, min(most_words, int(total // least_slots)))


def schedule(spark, quota: list[int], block: int, slots_per_task: int = 1 << 18) -> DataFrame:
    """(slot, src, k, words): the k-th block of source number src stands in the slot.  Two passes over the
    slot numbers; only counts for each task and source (tasks x sources numbers) come to the driver."""
    reach_workers(spark)
    wanted = np.array(quota, np.int64)
    blocks = -(-wanted // block)
    n = int(blocks.sum())
    if not n:
        return spark.createDataFrame([], "slot long, src int, k long, words long")
    edges = np.cumsum(wanted) / wanted.sum()
    edges[-1] = 1.0
    tasks = -(-n // slots_per_task)

    def sources(lo: int, hi: int) -> np.ndarray:
        at = (np.arange(lo, hi, dtype=np.uint64) * np.uint64(GOLDEN) >> np.uint64(11)).astype(np.float64) / (1 << 53)
        return np.searchsorted(edges, at, side="right")

    def count(batches):
        for batch in batches:
            for t in batch.column(0).to_pylist():
                c = np.bincount(sources(t * slots_per_task, min(n, (t + 1) * slots_per_task)), minlength=len(wanted))
                yield pa.record_batch([pa.array([t]), pa.array([c.tolist()], pa.list_(pa.int64()))], ["t", "c"])

    ranges = spark.range(0, tasks, 1, min(tasks, 2000))
    got = np.array([r["c"] for r in sorted(ranges.mapInArrow(count, "t long, c array<long>").collect(), key=lambda r: r["t"])], np.int64).reshape(-1, len(wanted))
    before = np.cumsum(got, axis=0) - got
    have = got.sum(axis=0)
    firsts = spark.createDataFrame([(t, before[t].tolist()) for t in range(tasks)], "t long, before array<long>")

    def give(batches):
        for batch in batches:
            for t, first in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                lo = t * slots_per_task
                src = sources(lo, min(n, lo + slots_per_task))
                order = np.argsort(src, kind="stable")
                begin = np.searchsorted(src[order], np.arange(len(wanted)))
                k = np.empty(len(src), np.int64)
                k[order] = np.arange(len(src)) - begin[src[order]]
                k += np.array(first)[src]
                ok = k < blocks[src]
                s, k, slot = src[ok], k[ok], (lo + np.arange(len(src)))[ok]
                yield pa.record_batch([pa.array(slot), pa.array(s, pa.int32()), pa.array(k), pa.array(np.minimum(block, wanted[s] - k * block))], ["slot", "src", "k", "words"])

    placed = firsts.repartition(min(tasks, 2000), "t").mapInArrow(give, "slot long, src int, k long, words long")
    short = [(i, int(have[i]), int(blocks[i])) for i in range(len(wanted)) if have[i] < blocks[i]]
    if short:  # a source that the points met too seldom: its last blocks follow at the end
        base, rows = n, []
        for i, a, b in short:
            rows.append((i, a, b, base, int(wanted[i])))
            base += b - a
        late = spark.createDataFrame(rows, "src int, a long, b long, base long, quota long").select("src", "a", "base", "quota", F.explode(F.sequence("a", F.col("b") - 1)).alias("k"))
        placed = placed.unionByName(late.select((F.col("base") + F.col("k") - F.col("a")).alias("slot"), "src", "k", F.least(F.lit(block).cast("long"), F.col("quota") - F.col("k") * block).alias("words")))
    return placed


class Mixture:
    """The spans of a mix: one row for each run of a document's words in a slot, and the sources' figures."""

    def __init__(self, documents: DataFrame, spans: DataFrame, sources: DataFrame):
        self.documents, self.spans, self.sources = documents, spans, sources


def mix(docs: DataFrame, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0, seed: int = 17, text: str = "text") -> Mixture:
    """Mix all documents.

    Null texts and texts without words have size 0 and are never taken; null sources are a
    source of their own, last in order; repeated rows are documents of their own; an empty
    table gives an empty mix.  Reruns agree: the shuffle is a hash of doc_id and the seed.
    ``spans`` has slot, row key (doc_id, salt, size), lap, from_word, to_word.
    """
    spark = docs.sparkSession
    rows = staged(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").alias("source"), words_of(text).alias("size"), F.xxhash64(F.lit(seed), "doc_id", F.xxhash64(text)).alias("salt")), "sizes")
    # One number for each source: a corpus has far fewer sources than documents.
    sizes = {r["source"]: r["n"] for r in rows.groupBy("source").agg(F.sum("size").alias("n")).collect()}
    wanted = targets(sizes, weights, share, most)
    names = list(wanted)
    quota = [min(int(wanted[s] + 0.5), int(most * sizes[s])) for s in names]
    block = block_words(float(sum(quota)))
    info = spark.createDataFrame([(s, i, sizes[s], float(wanted[s]), quota[i]) for i, s in enumerate(names)], "source string, src int, source_size long, target double, quota long")
    located = numbered(rows.join(info.alias("i"), rows["source"].eqNullSafe(F.col("i.source"))).select(rows["*"], "src", "source_size", "target", "quota"), ["src"], "salt", ["doc_id", "size"], "size", "position")
    # Lap after lap over the source's stream; a document meets the blocks that its words reach.
    laps = located.where("size > 0 and quota > 0").withColumn("lap", F.explode(F.sequence(F.lit(0), F.ceil(F.lit(most)).cast("int") - 1)))
    laps = laps.withColumn("lo", F.col("lap") * F.col("source_size") + F.col("position")).withColumn("hi", F.least(F.col("lo") + F.col("size"), F.col("quota"))).where("lo < hi")
    touched = laps.withColumn("k", F.explode(F.sequence(F.expr(f"lo div {block}"), F.expr(f"(hi - 1) div {block}"))))
    slots = schedule(spark, quota, block)
    spans = touched.join(slots, ["src", "k"]).withColumn("from_at", F.greatest("lo", F.col("k") * block)).withColumn("to_at", F.least("hi", F.col("k") * block + F.col("words")))
    spans = spans.select("slot", "doc_id", "salt", "size", "src", "position", "lap", (F.col("from_at") - F.col("lo")).alias("from_word"), (F.col("to_at") - F.col("lo")).alias("to_word"))
    return Mixture(located, spans, info)


def taken_words(mixture: Mixture) -> DataFrame:
    """Every document with its source's figures and the words that the mix takes of it, repeats counted."""
    taken = mixture.spans.groupBy("src", "position", "doc_id", "salt", "size").agg(F.sum(F.col("to_word") - F.col("from_word")).alias("taken"))
    d, t = mixture.documents.alias("d"), taken.alias("t")
    same = (F.col("d.src") == F.col("t.src")) & (F.col("d.position") == F.col("t.position")) & F.col("d.doc_id").eqNullSafe(F.col("t.doc_id")) & (F.col("d.salt") == F.col("t.salt")) & (F.col("d.size") == F.col("t.size"))
    return d.join(t, same, "left").select("d.doc_id", "d.source", "d.salt", "d.size", "d.source_size", "d.target", F.coalesce("t.taken", F.lit(0).cast("long")).alias("taken"))


def mixed_documents(docs: DataFrame, **how) -> DataFrame:
    """The mix as rows of docs: a document taken more than once is repeated, one of which only the
    first words are taken is cut after them, one that is not taken is left out.

    All columns stay as they are, whatever their names, but ``n_chars``, where there is one, follows a cut text.  Null
    and empty texts have no words and are left out; null sources and doc_ids are mixed like others; of rows that repeat
    doc_id and text the first by all their columns stands for all; very long texts are cut like others; an
    empty table gives no rows.
    """
    import re

    columns = docs.columns
    seed = how.get("seed", 17)
    taken = taken_words(mix(docs, **how)).groupBy("doc_id", "salt").agg(F.sum("taken").alias("__taken"), F.max("size").alias("__size"), F.count(F.lit(1)).alias("__rows"))
    taken = staged(taken, "taken")
    # A row travels as one struct, so no column of it meets a helper's name.
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in columns)).alias("__row"), F.col("doc_id").cast("long").alias("__id"), F.xxhash64(F.lit(seed), F.col("doc_id").cast("long"), F.xxhash64("text")).alias("__salt"))
    if not taken.where("__rows > 1").isEmpty():  # rows that are one and the same share what is taken of them
        again = taken.where("__rows > 1").select(F.col("doc_id").alias("__a"), F.col("salt").alias("__b"))
        same = F.col("__id").eqNullSafe(F.col("__a")) & (F.col("__salt") == F.col("__b"))
        some = packed.join(again, same, "left_semi").withColumn("__text", F.to_json("__row"))
        once = some.groupBy("__id", "__salt").agg(F.min_by("__row", "__text").alias("__row")).select("__row", "__id", "__salt")
        packed = packed.join(again, same, "left_anti").unionByName(once)
    t = taken.where("__taken > 0").select(F.col("doc_id").alias("__doc"), F.col("salt").alias("__hash"), "__taken", "__size")
    rows = packed.join(t, F.col("__id").eqNullSafe(F.col("__doc")) & (F.col("__salt") == F.col("__hash"))).select("__row", "__taken", "__size")
    word = re.compile(r"[^\x20\x09-\x0D]+")
    at, chars = columns.index("text"), columns.index("n_chars") if "n_chars" in columns else None

    def cut(text: str, words: int) -> str:
        for i, m in enumerate(word.finditer(text), 1):
            if i == words:
                return text[: m.end()]
        return text

    def give(batches):
        for batch in batches:
            n, size = batch.column("__taken").to_numpy(), batch.column("__size").to_numpy()
            whole, part = n // size, n % size
            base = pa.RecordBatch.from_arrays(batch.column("__row").flatten(), columns)
            yield base.take(pa.array(np.repeat(np.arange(len(n)), whole)))
            some = np.flatnonzero(part)
            if len(some):
                few = base.take(pa.array(some))
                texts = [cut(t, int(k)) for t, k in zip(few.column(at).to_pylist(), part[some])]
                arrays = list(few.columns)
                arrays[at] = pa.array(texts, few.schema.field(at).type)
                if chars is not None:
                    arrays[chars] = pa.array([len(x) for x in texts], few.schema.field(chars).type)
                yield pa.record_batch(arrays, schema=few.schema)

    return rows.mapInArrow(give, docs.schema)
