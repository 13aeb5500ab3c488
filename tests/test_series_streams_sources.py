"""Time series identities and examples, streams against batch, sources and SQL."""

import random

import pytest
from pyspark.sql import functions as F

from temporal_rules import sqlext
from temporal_rules.functions import timeseries as ts
from temporal_rules.model import HI, LO, STEPS, Range, TemporalRelation
from temporal_rules.operators import merge
from temporal_rules.sources import tables
from temporal_rules.streaming import operators as st


def series(spark, values, k="a"):
    return ts.Series(spark.createDataFrame([(k, t, float(v)) for t, v in values], "k string, t long, v double"), ("k",))


def vals(s):
    return {x.t: x.v for x in s.df.collect()}


def test_rolling_and_averages(spark):
    s = series(spark, [(1, 1), (2, 2), (3, 2), (4, 7)])
    assert vals(ts.rolling(s, 3)) == {3: 5, 4: 11}
    assert vals(ts.rolling(s, 3, set_semantics=True)) == {3: 3, 4: 9}
    assert vals(ts.rolling(s, 3, "max", partial=True)) == {1: 1, 2: 2, 3: 2, 4: 7}
    by_rules = {}
    for x in ts.rolling_by_rules(s, 3).df.collect():
        by_rules.setdefault(x[LO], []).append(x.v)
    assert sorted(by_rules[4]) == [2, 2, 7] and sorted(by_rules[3]) == [1, 2, 2]
    assert vals(ts.cma(s, 3)) == pytest.approx({2: 5 / 3, 3: 11 / 3})
    assert vals(ts.stock_to_flow(series(spark, [(1, 5), (2, 8), (4, 1)]))) == {2: 3}
    back = ts.stock_to_flow(ts.flow_to_stock(s))
    assert vals(back) == {t: v for t, v in vals(s).items() if t > 1}
    assert vals(ts.flow_to_stock(s, block=2)) == vals(ts.flow_to_stock(s)) == {1: 1, 2: 3, 3: 5, 4: 12}
    assert vals(ts.upsample(series(spark, [(0, 0), (7, 14)]))) == {t: 2.0 * t for t in range(8)}
    assert vals(ts.upsample(series(spark, [(0, 5), (3, 14)]), method="hold")) == {0: 5, 1: 5, 2: 5, 3: 14}
    assert vals(ts.downsample(s, F.expr("t div 2"), "sum")) == {0: 1, 1: 4, 2: 7}
    f = ts.frequency(series(spark, [(1, 1)])).first()
    assert f.regular and f.least is None


def test_ema_forms_agree(spark):
    rng = random.Random(2)
    rows = [(k, t, rng.random() * 100) for k in "abc" for t in range(3 if k == "c" else 700)]
    s = ts.Series(spark.createDataFrame(rows, "k string, t long, v double"), ("k",))
    for n in (1, 5, 30):
        k = 2 / (n + 1)
        want = {}
        for name in "abc":
            v = [x for q, _, x in rows if q == name]
            if len(v) >= n:
                y = sum(v[:n]) / n
                want[name, n - 1] = y
                for t in range(n, len(v)):
                    y = k * v[t] + (1 - k) * y
                    want[name, t] = y
        for out in (ts.ema(s, n), ts.ema_blocks(s, n, 64)):
            assert {(x.k, x.t): x.v for x in out.df.collect()} == pytest.approx(want, rel=1e-9)
    assert vals(ts.ema(series(spark, [(1, 4), (2, 8)]), 3, "first")) == {1: 4, 2: 6}


def test_decomposition_adds_up(spark):
    rng = random.Random(4)
    s = series(spark, [(t, 3 * t + [5, -2, 0, 1, -4, 2, -2][t % 7] + rng.random()) for t in range(60)])
    d = ts.decompose(s, 7)
    whole = ts.add(ts.add(d.trend, d.seasonal), d.residual)
    assert vals(whole) == pytest.approx({t: v for t, v in vals(s).items() if 3 <= t <= 56})
    assert len(set(round(v, 9) for v in vals(d.seasonal).values())) == 7
    even = ts.decompose(s, 12)
    assert min(vals(even.trend)) == 6
    per = ts.decompose(s, 7, divisor="periods", periods=9)
    assert vals(per.seasonal)[10] == pytest.approx(vals(d.seasonal)[10] * 8 / 9)


def stream_of(spark, tmp_path, df, files=3, schema=None):
    """The rows of a frame as a stream of files in a fixed order."""
    path = str(tmp_path / "in")
    df.repartition(files).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def drain(sdf, name, mode):
    q = sdf.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return sdf.sparkSession.table(name)


@pytest.fixture(scope="module")
def facts(spark):
    rng = random.Random(7)
    rows = []
    for _ in range(60):
        a = rng.randrange(200)
        rows.append(("k%d" % rng.randrange(3), a, a + rng.randrange(12)))
    df = spark.createDataFrame(rows, f"k string, {LO} long, {HI} long")
    return df.withColumn("at", F.timestamp_millis(F.col(LO)))


def stateful(spark):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def islands(df, keys=("k",)):
    return {tuple(x) for x in merge.coalesce(TemporalRelation(df.select(*keys, LO, HI), keys, STEPS)).df.collect()}


def test_stream_diamond_and_sessions(spark, tmp_path, facts):
    sdf = stream_of(spark, tmp_path, facts)
    got = drain(st.stream_diamond(sdf, "past", Range(1, 4)).select("k", LO, HI), "diamond", "append")
    assert sorted(map(tuple, got.collect())) == sorted((x.k, x[LO] + 1, x[HI] + 4) for x in facts.collect())
    for bad in (("alwayspast", Range(0, 1)), ("past", Range(0, None))):
        with pytest.raises(ValueError):
            st.stream_diamond(sdf, *bad)
    out = drain(st.session_merge(sdf.withWatermark("at", "1 hour"), ["k"], "at", "20 milliseconds"), "sessions", "complete")
    assert out.agg(F.sum("n")).first()[0] == 60
    out = drain(st.windowed(sdf.withColumn("value", F.lit(1.0)).withWatermark("at", "1 hour"), ["k"], "at", "50 milliseconds", "25 milliseconds"), "windows", "complete")
    assert out.agg(F.sum("n")).first()[0] == 120


def test_stream_merge_and_box_end_as_batch(spark, tmp_path, facts):
    stateful(spark)
    sdf = stream_of(spark, tmp_path, facts).withWatermark("at", "1 hour")
    got = drain(st.stream_merge(sdf, ["k"], "update"), "merged", "update")
    assert islands(got) == islands(facts) and islands(facts) <= {tuple(x) for x in got.collect()}
    box = drain(st.stream_box(sdf, ["k"], "alwayspast", Range(0, 5)), "boxed", "update")
    assert islands(box) == {(k, a + 5, b) for k, a, b in islands(facts) if a + 5 <= b}


def test_stream_join_as_batch(spark, tmp_path, facts):
    other = facts.select("k", (F.col(LO) + 3).alias(LO), (F.col(HI) + 3).alias(HI), F.timestamp_millis(F.col(LO) + 3).alias("at"), F.lit(1).alias("w"))
    l = stream_of(spark, tmp_path / "l", facts).withWatermark("at", "1 hour")
    r = stream_of(spark, tmp_path / "r", other).withWatermark("at", "1 hour")
    got = drain(st.stream_join(l, r, ["k"], "at", "at", "1 minute"), "joined", "append")
    want = facts.alias("l").join(other.alias("r"), "k").where(f"l.{LO} <= r.{HI} and r.{LO} <= l.{HI}").count()
    assert got.count() == want


def test_two_sided_answers_by_ticks():
    rng = random.Random(3)
    for _ in range(300):
        def some():
            out = []
            for _ in range(rng.randrange(4)):
                a = rng.randrange(20)
                out, _, _ = st._islands(out, a, a + rng.randrange(4))
            return out

        l, r = some(), some()
        hl, hr = ({c for a, b in x for c in range(a, b + 1)} for x in (l, r))
        lo = rng.randrange(3)
        hi = lo + rng.randrange(4)
        cells = lambda x: {c for a, b in x for c in range(a, b + 1)}
        assert cells(st.answer("minus", l, r, (0, 0))) == hl - hr
        since = {t for t in range(-20, 60) if any(t - o in hr and all(x in hl for x in range(t - o + 1, t)) for o in range(lo, hi + 1))}
        until = {t for t in range(-20, 60) if any(t + o in hr and all(x in hl for x in range(t + 1, t + o)) for o in range(lo, hi + 1))}
        assert cells(st.answer("since", l, r, (lo, hi))) == since and cells(st.answer("until", l, r, (lo, hi))) == until


def test_sources_and_sql(spark, tmp_path):
    df = spark.createDataFrame([("a", 0, 5), ("a", 5, 9), ("b", 2, 4000), ("c", 900, None)], "k string, s long, e long")
    r = tables.facts_from(df, ["k"], "s", "e")
    path = str(tmp_path / "facts")
    tables.write_facts(r, path, name="held")
    back = tables.read_facts(spark, path, ["k"], name="held")
    assert sorted(map(tuple, back.to_df().collect())) == sorted(map(tuple, r.to_df().collect()))
    near = tables.read_facts(spark, path, ["k"], name="held", span=(0, 30))
    assert {x.k for x in near.df.collect()} == {"a", "b"}
    for fmt in ("json", "csv", "orc"):
        p = str(tmp_path / fmt)
        df.write.format(fmt).save(p)
        assert tables.load_table(spark, p, fmt, "k string, s long, e long").count() == 4
    with pytest.raises(ValueError):
        tables.load_table(spark, path, "csv")
    rules = tmp_path / "rules.txt"
    rules.write_text("p(X) :- q(X).\n")
    assert tables.load_rules(spark, str(rules)) == "p(X) :- q(X)."
    sqlext.register_sql(spark)
    sqlext.register_view(r, "held")
    assert [tuple(x) for x in spark.sql("select k, t_start, t_end from held where k = 'a'").collect()] == [("a", 0, 9)]
    assert [tuple(x) for x in spark.sql("select * from unroll_pattern(0, 1, 30, 1, 25, 95)").collect()] == [(1, 30, 31), (2, 60, 61), (3, 90, 91)]
    hold = tables.hold_until_next(spark.createDataFrame([("a", 1), ("a", 4)], "k string, t long"), ["k"], "t", STEPS)
    assert sorted(map(tuple, hold.to_df(flags=False).collect())) == [("a", 1, 3), ("a", 4, None)]
