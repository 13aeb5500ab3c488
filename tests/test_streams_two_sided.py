"""Difference, since and until on streams against batch, with a state that stays small."""

import json
import random
import time

import pandas as pd
import pytest
from pyspark.sql import functions as F

from temporal_rules.model import HI, LO, STEPS, Range, TemporalRelation
from temporal_rules.operators import binary, joins, merge, unary
from temporal_rules.streaming import operators as st

SCHEMA = f"k string, {LO} long, {HI} long"


def rows_of(seed, n=80):
    rng = random.Random(seed)
    return sorted((f"k{rng.randrange(3)}", a := 10 + rng.randrange(390), a + rng.randrange(14)) for _ in range(n))


def stream(spark, path, rows):
    """Files in order of time; the last ones only move the watermark on."""
    for i in range(8):
        some = [r for r in rows if i * 50 <= r[1] < (i + 1) * 50]
        spark.createDataFrame(some + [("clock", i * 50 + 1, i * 50 + 1)], SCHEMA).withColumn("at", F.timestamp_millis(F.col(LO))).coalesce(1).write.mode("append").parquet(str(path))
        time.sleep(0.02)
    for t in (5_000, 6_000):
        spark.createDataFrame([("clock", t, t)], SCHEMA).withColumn("at", F.timestamp_millis(F.col(LO))).coalesce(1).write.mode("append").parquet(str(path))
        time.sleep(0.02)
    schema = spark.read.parquet(str(path)).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(path)).withWatermark("at", "0 milliseconds")


@pytest.mark.parametrize("kind", ["minus", "since", "until"])
def test_streams_answer_as_batch(spark, tmp_path, kind):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    a, b = rows_of(1), rows_of(2, 50)
    l, r = stream(spark, tmp_path / "l", a), stream(spark, tmp_path / "r", b)
    rng = Range(1, 6, False, True)
    sdf = st.stream_minus(l, r, ["k"]) if kind == "minus" else (st.stream_since if kind == "since" else st.stream_until)(l, r, ["k"], rng)
    q = sdf.writeStream.format("memory").queryName(f"two_{kind}").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(240)
    rel = lambda rows: TemporalRelation(spark.createDataFrame(rows, SCHEMA), ("k",), STEPS)
    ra, rb = merge.coalesce(rel(a)), rel(b)
    want = joins.temporal_minus(ra, rb, ["k"]) if kind == "minus" else (binary.since if kind == "since" else binary.until)(ra, rb, rng, ["k"])
    got = merge.coalesce(TemporalRelation(spark.table(f"two_{kind}").where("k <> 'clock'").select("k", LO, HI), ("k",), STEPS))
    assert {tuple(x) for x in got.df.collect()} == {tuple(x) for x in merge.coalesce(want).df.collect()} != set()


class Handle:
    def __init__(self):
        self.value, self.timers = None, set()

    def getValueState(self, *_):
        return self

    def exists(self):
        return self.value is not None

    def get(self):
        return self.value

    def update(self, v):
        self.value = v

    def clear(self):
        self.value = None

    def registerTimer(self, t):
        self.timers.add(t)


class Times:
    def __init__(self, now):
        self.now = now

    def getCurrentWatermarkInMs(self):
        return self.now

    getExpiryTimeInMs = getCurrentWatermarkInMs


@pytest.mark.parametrize("kind", ["minus", "since", "until"])
def test_state_of_a_busy_key_stays_small(kind):
    p, h = st._Ordered(["k"], kind, (1, 4), 1.0), Handle()
    p.init(h)
    out, largest, every = [], 0, {"l": [], "r": []}
    for t in range(0, 1000, 5):
        now = t - 20
        for due in sorted(x for x in h.timers if x <= now):
            h.timers.discard(due)
            for pdf in p.handleExpiredTimer(("a",), Times(now), Times(due)):
                out += pdf[[LO, HI]].values.tolist()
        facts = [("l", t, t + 7 if t % 40 else t + 1)] + ([("r", t, t)] if t % 15 == 0 else [])
        for s, lo, hi in facts:
            every[s], _, _ = st._islands(every[s], lo, hi)
        list(p.handleInputRows(("a",), iter([pd.DataFrame(facts, columns=["side", "lo", "hi"])]), Times(now)))
        largest = max(largest, sum(len(v) for v in json.loads(h.value[0]).values() if isinstance(v, list)))
    for due in [2_000, 3_000]:
        for pdf in p.handleExpiredTimer(("a",), Times(due), Times(due)):
            out += pdf[[LO, HI]].values.tolist()
    cells = lambda rows: {c for lo, hi in rows for c in range(lo, hi + 1)}
    assert largest < 20 and h.value is None
    assert cells(out) == cells(st.answer(kind, every["l"], every["r"], (1, 4)))


def test_open_ends_of_ranges(spark):
    dense = TemporalRelation(spark.createDataFrame([("a", 4, 11), ("b", 3, 3)], SCHEMA), ("k",))
    rng = Range(1, 3, True, True)
    moved = st.stream_diamond(dense.df, "past", rng, scale=2)
    assert sorted(map(tuple, moved.collect())) == sorted(map(tuple, unary.sometime_past(dense, rng).df.collect()))
    for bad in (("past", Range(0, 1)), ("alwayspast", Range(0, None))):
        with pytest.raises(ValueError):
            st.stream_box(dense.df, ["k"], *bad)
