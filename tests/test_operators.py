"""Operators against their truth definitions, evaluated cell by cell on random small inputs."""

import random
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from temporal_rules.model import DAYS, HI, LO, NEG, POS, STEPS, Range, TemporalRelation, always_true, never, relation
from temporal_rules.operators import aggregates, binary, joins, merge, unary
from temporal_rules.operators.unary import as_transform
from temporal_rules.workloads import queries

SPAN = range(-90, 160)  # cells looked at; far beyond what the inputs can reach


def rel(spark, rows, timeline=DAYS, keys=("k",)):
    schema = ", ".join(f"{k} string" for k in keys) + f", {LO} long, {HI} long"
    return TemporalRelation(spark.createDataFrame(rows, schema), tuple(keys), timeline)


def cells(r):
    out = defaultdict(set)
    for row in r.df.collect():
        out[tuple(row[k] for k in r.keys)] |= {c for c in SPAN if row[LO] <= c <= row[HI]}
    return {k: v for k, v in out.items() if v}


def random_rows(rng, cases, many=4, hi=24):
    rows = []
    for c in range(cases):
        for _ in range(rng.randrange(many + 1)):
            a = rng.randrange(hi)
            rows.append((f"c{c}", a, a + rng.randrange(12)))
    return rows or [("c0", 0, 3)]


def ranges(dense):
    out = [Range(0, 0), Range(0, 2), Range(1, 3), Range(2, 5), Range(2, 2)]
    return out + [Range(0, 2, True, False), Range(0, 2, False, True), Range(1, 3, True, True), Range(0, 3, True, True)] if dense else out + [Range(0, 2, True, False), Range(0, 3, False, True)]


def offsets(rng, dense):
    """Distances in the operator's range: all multiples of 1/8 on dense time, finer than the points looked at."""
    if not dense:
        return [x for x in range(rng.lo, rng.hi + 1) if rng.holds(x)]
    return [x / 8 for x in range(8 * rng.lo, 8 * rng.hi + 1) if rng.holds(x / 8)]


def cell_of(x, dense):
    if not dense:
        return x
    import math

    return 2 * int(x) if x == int(x) else 2 * math.floor(x) + 1


def witness(cell, dense):
    """Sample points of a cell."""
    if not dense:
        return [cell]
    return [cell // 2] if cell % 2 == 0 else [cell // 2 + 0.25, cell // 2 + 0.5, cell // 2 + 0.75]


def brute(op, held, rng, dense):
    out = set()
    offs = offsets(rng, dense)
    sign = -1 if op in ("past", "alwayspast") else 1
    test = all if op.startswith("always") else any
    for c in range(-40, 80):
        if all(test(cell_of(t + sign * o, dense) in held for o in offs) for t in witness(c, dense)):
            out.add(c)
    return out


@pytest.mark.parametrize("timeline", [DAYS, STEPS], ids=["dense", "discrete"])
@pytest.mark.parametrize("op", list(unary.OPERATORS))
def test_unary_by_definition(spark, timeline, op):
    rng = random.Random(len(op))
    rows = random_rows(rng, 40)
    r = rel(spark, rows, timeline)
    held = cells(r)
    for index in ranges(timeline.dense):
        got = cells(unary.OPERATORS[op](r, index))
        for k, h in held.items():
            assert {c for c in got.get(k, set()) if -40 <= c < 80} == brute(op, h, index, timeline.dense), (k, index)


@pytest.mark.parametrize("timeline", [DAYS, STEPS], ids=["dense", "discrete"])
@pytest.mark.parametrize("name", ["since", "until"])
def test_since_until_by_definition(spark, timeline, name):
    rng = random.Random(11)
    a, b = random_rows(rng, 30, 3, 14), random_rows(rng, 30, 2, 14)
    ra, rb = rel(spark, a, timeline), rel(spark, b, timeline)
    ha, hb = cells(ra), cells(rb)
    dense = timeline.dense
    grid = [x / 16 for x in range(-160, 560)] if dense else list(range(-10, 40))
    for index in ranges(dense):
        got = cells(getattr(binary, name)(ra, rb, index, ["k"]))
        for k in set(ha) | set(hb):
            want = set()
            for c in range(0, 50) if dense else range(0, 30):
                ok = []
                for t in witness(c, dense):
                    hit = False
                    for o in offsets(index, dense):
                        s = t - o if name == "since" else t + o
                        if cell_of(s, dense) in hb.get(k, ()) and all(cell_of(x, dense) in ha.get(k, ()) for x in grid if min(s, t) < x < max(s, t)):
                            hit = True
                            break
                    ok.append(hit)
                if all(ok):
                    want.add(c)
            top = 50 if dense else 30
            assert {c for c in got.get(k, set()) if 0 <= c < top} == want, (k, index)


def test_coalesce_minus_join_sets(spark):
    rng = random.Random(2)
    a, b = random_rows(rng, 60, 5), random_rows(rng, 60, 5)
    ra, rb = rel(spark, a), rel(spark, b)
    ha, hb = cells(ra), cells(rb)
    for m in (merge.coalesce(ra), merge.coalesce_hot(ra, 7)):
        assert cells(m) == ha
        per = defaultdict(list)
        for x in m.df.collect():
            per[x.k].append((x[LO], x[HI]))
        assert all(p[1] + 1 < q[0] for v in per.values() for p, q in zip(sorted(v), sorted(v)[1:]))
    want = lambda f: {k: f(ha.get(k, set()), hb.get(k, set())) for k in set(ha) | set(hb) if f(ha.get(k, set()), hb.get(k, set()))}
    assert cells(joins.temporal_minus(ra, rb, ["k"])) == want(set.difference)
    assert cells(joins.interval_except(ra, rb)) == want(set.difference)
    assert cells(joins.interval_intersect(ra, rb)) == want(set.intersection)
    assert cells(joins.interval_union(ra, rb)) == want(set.union)
    assert cells(joins.temporal_semi(ra, rb, ["k"])) == want(set.intersection)
    assert cells(merge.novel(ra, merge.coalesce(rb))) == want(set.difference)
    gap = cells(merge.coalesce(ra, 3))
    for k, h in ha.items():
        s = sorted(h)
        assert gap[k] == h | {c for x, y in zip(s, s[1:]) if y - x <= 4 for c in range(x, y)}


def test_streaming_states_end_in_the_islands(spark):
    rng = random.Random(9)
    rows = [(k, lo, hi, i) for i, (k, lo, hi) in enumerate(random_rows(rng, 20, 6))]
    df = spark.createDataFrame(rows, f"k string, {LO} long, {HI} long, seq int")
    r = TemporalRelation(df, ("k",))
    got = merge.stream_states(r, "seq")
    assert cells(got) == cells(r)
    islands = {tuple(x) for x in merge.coalesce(r).df.collect()}
    assert islands <= {tuple(x) for x in got.df.collect()}


def test_streaming_states_of_many_keys(spark):
    """Batches cut keys anywhere; no Python call is made for each key."""
    rng = random.Random(21)
    rows = [(rng.randrange(150) if rng.random() < 0.6 else None, lo, lo + rng.randrange(6), i) for i, lo in enumerate(rng.randrange(200) for _ in range(400))]
    df = spark.createDataFrame(rows, f"k int, {LO} long, {HI} long, seq int")
    want = []
    for k in {x[0] for x in rows}:
        seen = []
        for _, a, b, _ in (x for x in rows if x[0] == k):
            if any(x <= a and b <= y for x, y in seen):
                continue
            touch = [(x, y) for x, y in seen if x <= b + 1 and a <= y + 1]
            a, b = min([a, *(x for x, _ in touch)]), max([b, *(y for _, y in touch)])
            seen = [s for s in seen if s not in touch] + [(a, b)]
            want.append((k, a, b))
    states = merge.stream_states(TemporalRelation(df, ("k",)), "seq").df
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = [tuple(x) for x in states.collect()]
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    order = lambda x: (x[0] is None, x[0] or 0, *x[1:])
    assert sorted(got, key=order) == sorted(want, key=order)
    assert "FlatMapGroups" not in states._jdf.queryExecution().toString()


def test_keyless_join_of_long_and_short_facts(spark):
    """Facts that only ask on a level do not meet each other there, and a join of coalesced sides is coalesced."""
    rng = random.Random(8)
    a = [(f"a{i}", lo, lo + (900 if i % 9 == 0 else rng.randrange(5))) for i, lo in enumerate(rng.randrange(1000) for _ in range(60))]
    b = [(f"b{i}", lo, lo + (60 if i % 7 == 0 else rng.randrange(5))) for i, lo in enumerate(rng.randrange(1000) for _ in range(60))]
    got = joins.temporal_join(merge.coalesce(rel(spark, a, keys=("a",))), merge.coalesce(rel(spark, b, keys=("b",))), [], bucket=5)
    want = sorted((x[0], y[0], max(x[1], y[1]), min(x[2], y[2])) for x in a for y in b if max(x[1], y[1]) <= min(x[2], y[2]))
    assert sorted(map(tuple, got.df.collect())) == want
    assert got.coalesced
    assert "__way" in got.df._jdf.queryExecution().optimizedPlan().toString()


def test_theta_query_exchanges_no_result(spark, sf):
    """Above the join of the two sides nothing is exchanged."""
    plan = queries.QUERIES["temporal_join_theta"](spark, sf)._jdf.queryExecution().sparkPlan().toString()
    assert "SortMergeJoin" in plan or "HashJoin" in plan
    above = plan[: min(x for x in (plan.find("SortMergeJoin"), plan.find("HashJoin")) if x >= 0)]
    assert "Window" not in above and "Aggregate" not in above


def test_keyless_join_and_minus(spark):
    rng = random.Random(5)
    a = [(f"a{i}", lo, hi) for i, (_, lo, hi) in enumerate(random_rows(rng, 12, 5))] + [("inf", NEG, 5), ("all", NEG, POS)]
    b = [(f"b{i}", lo, hi) for i, (_, lo, hi) in enumerate(random_rows(rng, 12, 5))] + [("tail", 20, POS)]
    ra, rb = rel(spark, a, keys=("a",)), rel(spark, b, keys=("b",))
    got = sorted(map(tuple, joins.temporal_join(ra, rb, [], bucket=3).df.collect()))
    want = sorted((x[0], y[0], max(x[1], y[1]), min(x[2], y[2])) for x in a for y in b if max(x[1], y[1]) <= min(x[2], y[2]))
    assert got == want == sorted(map(tuple, joins.temporal_join(ra, rb, []).df.collect()))
    hb = set().union(*cells(rb).values())
    assert cells(joins.temporal_minus(ra, rb, [])) == {k: v - hb for k, v in cells(ra).items() if v - hb}
    assert cells(joins.temporal_minus(ra, rel(spark, b, keys=("b",)).where(F.lit(False)), [])) == cells(ra)


def test_chains_in_all_placements(spark):
    rng = random.Random(8)
    r = rel(spark, random_rows(rng, 80, 5))
    held = cells(r)
    for _ in range(10):
        ops = [(rng.choice(list(unary.OPERATORS)), rng.choice([Range(0, 1), Range(1, 2), Range(0, 2), Range(0, 1, True, False), Range(1, 3, False, True)])) for _ in range(rng.randrange(1, 4))]
        results = [cells(merge.coalesce(unary.apply_chain(r, ops, p, f))) for p in ("minimal", "earliest", "always") for f in (True, False)]
        assert all(x == results[0] for x in results), ops
        for k in list(held)[:15]:
            h = held[k]
            for op, index in ops:
                h = brute(op, h, index, True)
            assert results[0].get(k, set()) == h, (k, ops)


def test_worked_examples(spark):
    shop = relation(spark.createDataFrame([("A", 5, 6)], "x string, s long, e long"), ["x"], "s", "e", end_open=False)
    assert [tuple(x) for x in unary.sometime_past(shop, Range(0, 12)).to_df().collect()] == [("A", 5, 18, False, False)]
    zero = relation(spark.createDataFrame([("A", 0)], "x string, s long"), ["x"], "s", "s", end_open=False)
    assert [tuple(x)[1:3] for x in unary.apply_chain(zero, [("future", Range(1, 3))]).to_df().collect()] == [(-3, -1)]
    assert [tuple(x)[1:3] for x in unary.apply_chain(zero, [("future", Range(1, 3)), ("past", Range(2, 5))]).to_df().collect()] == [(-1, 4)]
    assert [tuple(x)[1:3] for x in unary.apply_chain(zero, [("future", Range(1, 3)), ("past", Range(2, 5)), ("alwayspast", Range(0, 3))]).to_df().collect()] == [(2, 4)]
    assert unary.apply_chain(zero, [("future", Range(1, 3)), ("alwayspast", Range(0, 3))]).to_df().collect() == []
    moves = unary.compose([as_transform("future", Range(1, 3)), as_transform("past", Range(2, 5))])
    assert (moves[0].start, moves[0].end) == (-1, 4)
    # Stakes in tenths of a year: three years without a gap of more than half a year.
    stake = spark.createDataFrame([("A", "B", 1, 5), ("A", "B", 4, 11), ("A", "B", 15, 37), ("A", "B", 37, 42)], "x string, y string, s long, e long")
    r = relation(stake.withColumn("n", F.monotonically_increasing_id()), ["x", "y"], "s", "e")
    long = unary.apply_chain(r, [("past", Range(0, 5)), ("alwayspast", Range(0, 30))])
    assert [tuple(x) for x in long.to_df().collect()] == [("A", "B", 31, 47, False, True)]
    one_by_one = merge.stream_states(unary.sometime_past(r.with_df(r.df.withColumn("at", F.col(LO))), Range(0, 5)), LO)
    partial = unary.shift_ends(one_by_one, as_transform("alwayspast", Range(0, 30)))
    assert {tuple(x)[2:4] for x in partial.to_df().collect()} == {(31, 42), (31, 47)}
    goes = relation(spark.createDataFrame([("A", "C", 15, 17), ("B", "C", 21, 23)], "x string, m string, s long, e long"), ["x", "m"], "s", "e")
    sale = relation(spark.createDataFrame([("C", 14, 16)], "m string, s long, e long"), ["m"], "s", "e")
    assert [tuple(x) for x in joins.temporal_join(goes, sale, ["m"]).to_df().collect()] == [("A", "C", 15, 16, False, True)]
    share = relation(spark.createDataFrame([("A", "B", 3, 9)], "x string, y string, s long, e long"), ["x", "y"], "s", "e")
    for open_, want in ((True, [(3, 3)]), (False, [])):
        owner = joins.temporal_minus(unary.always_future(share, Range(0, 1)), unary.sometime_past(share, Range(0, 1, open_, False)), ["x", "y"])
        assert [tuple(x)[2:4] for x in owner.to_df().collect()] == want


def test_unbounded_ranges(spark):
    r = rel(spark, [("f", 4, 8), ("p", NEG, 8), ("u", 4, POS)])
    get = lambda x: {q.k: (q[LO], q[HI]) for q in x.df.collect()}
    inf = Range(1, None)
    assert get(unary.sometime_past(r, inf)) == {"f": (6, POS), "p": (NEG, POS), "u": (6, POS)}
    assert get(unary.sometime_future(r, inf)) == {"f": (NEG, 6), "p": (NEG, 6), "u": (NEG, POS)}
    assert get(unary.always_past(r, inf)) == {"p": (NEG, 10)}
    assert get(unary.always_future(r, inf)) == {"u": (2, POS)}
    assert get(merge.coalesce(r)) == get(r)
    assert get(joins.temporal_minus(r, rel(spark, [("f", NEG, POS), ("p", 0, 3), ("u", 9, POS)]), ["k"])) in ({"p": (4, 8), "u": (4, 8)}, {"p": (NEG, -1), "u": (4, 8)})
    assert always_true(spark).df.count() == 1 and never(spark).df.count() == 0
    for bad in ((-1, 2, False, False), (3, 2, False, False), (2, 2, True, False)):
        with pytest.raises(ValueError):
            Range(*bad)


def test_aggregates_by_cells(spark):
    rng = random.Random(6)
    rows = [("g%d" % rng.randrange(4), "c%d" % i, float(rng.randrange(-3, 9)), lo, hi) for i, (_, lo, hi) in enumerate(random_rows(rng, 20, 5))]
    df = spark.createDataFrame(rows, f"g string, c string, v double, {LO} long, {HI} long")
    r = TemporalRelation(df, ("g", "c", "v"))
    for f, calc in (("sum", sum), ("count", len), ("min", min), ("max", max), ("avg", lambda v: sum(v) / len(v))):
        got = {}
        for x in aggregates.agg_at_each_time(r, ["g"], f, "v").df.collect():
            for c in range(x[LO], x[HI] + 1):
                assert (x.g, c) not in got
                got[x.g, c] = float(x.value)
        want = defaultdict(list)
        for g, _, v, lo, hi in rows:
            for c in range(lo, hi + 1):
                want[g, c].append(v)
        assert got == pytest.approx({k: calc(v) for k, v in want.items()}, abs=1e-6)
    best = aggregates.monotonic(TemporalRelation(spark.createDataFrame([("g", "c", 2.0, 0, 9), ("g", "c", 5.0, 4, 9), ("g", "d", 1.0, 0, 9)], df.schema), r.keys), ["g"], "msum", "v", ["c"])
    assert sorted((float(x.value), x[LO], x[HI]) for x in best.df.collect()) == [(3.0, 0, 3), (6.0, 4, 9)]
    covered = {x.g: x.covered for x in aggregates.covered_time(r, ["g"]).collect()}
    assert set(covered) == {x[0] for x in rows}


def test_monotonic_aggregates_by_cells(spark):
    """Contributors with many facts, nulls and NaN, cut by batches anywhere; their facts are not joined with their stretches."""
    rng = random.Random(31)
    pick = lambda: rng.choice([None, float("nan"), 1.0, 2.0, 3.0, -4.0])
    rows = [("g%d" % rng.randrange(3), "c%d" % (rng.randrange(40) if rng.random() < 0.5 else 0), pick(), lo, lo + rng.randrange(12)) for lo in (rng.randrange(60) for _ in range(150))]
    rows += [("g0", "c0", 2.5, NEG, 7), ("g1", "c1", 2.5, 50, POS), ("g2", "c2", None, NEG, POS)]
    df = spark.createDataFrame(rows, f"g string, c string, v double, {LO} long not null, {HI} long not null")
    r = TemporalRelation(df, ("g", "c", "v"))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "5")
    try:
        for least in (False, True):
            best = aggregates.best_at_each_time(r, ["g", "c"], "v", "best", least)
            got = {}
            facts = [tuple(x) for x in best.df.collect()]
            for g, c, v, lo, hi in facts:
                for t in range(max(lo, -3), min(hi, 80) + 1):
                    assert (g, c, t) not in got
                    got[g, c, t] = repr(v)
            want = defaultdict(list)
            for g, c, v, lo, hi in rows:
                for t in range(max(lo, -3), min(hi, 80) + 1):
                    want[g, c, t].append(v)

            def calc(vs):
                known = sorted((v for v in vs if v is not None), key=lambda v: (v != v, 0 if v != v else v))
                return repr(known[0 if least else -1] if known else None)

            assert got == {k: calc(v) for k, v in want.items()}
            islands = merge.coalesce(best, force=True).df.collect()
            assert sorted(map(repr, facts)) == sorted(repr(tuple(x)) for x in islands)
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    plan = aggregates.monotonic(r, ["g"], "msum", "v", ["c"]).df._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange hashpartitioning") == 2


def test_thirteen_relations(spark):
    pairs = [(a, b, c, d) for a in range(6) for b in range(a, 6) for c in range(6) for d in range(c, 6)]
    df = spark.createDataFrame(pairs, "a int, b int, c int, d int")
    got = df.select("*", joins.relation13(*(F.col(x) for x in "abcd")).alias("r")).collect()
    back = {(x.a, x.b, x.c, x.d): x.r for x in got}
    assert set(back.values()) == set(joins.RELATIONS)
    other = dict(before="after", meets="met_by", overlaps="overlapped_by", starts="started_by", during="contains", finishes="finished_by", equals="equals")
    other |= {v: k for k, v in other.items()}
    assert all(back[c, d, a, b] == other[r] for (a, b, c, d), r in back.items())
