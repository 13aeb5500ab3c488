"""Language, analysis, rewriting, evaluation variants, patterns and termination."""

import random

import pytest

from temporal_rules import baselines
from temporal_rules.model import DAYS, HI, LO, Range, TemporalRelation, points, relation, timeless
from temporal_rules.operators import merge, unary
from temporal_rules.plans import analysis
from temporal_rules.plans.language import Assign, Compare, RuleError, Var, parse, validate
from temporal_rules.plans.patterns import PatternRelation, accelerate_constant, pattern_join, pattern_pattern_join, recognise
from temporal_rules.plans.rewrite import canonicalise, fuse_chains, simplify
from temporal_rules.plans.runtime import Engine, Options, placements, to_plain, to_temporal


def rel(spark, rows, *keys, timeline=DAYS):
    """Rows of keys, start, end with half-open intervals."""
    names = [*keys, "s", "e"]
    return relation(spark.createDataFrame(rows, names), list(keys), "s", "e", timeline)


def got(r):
    return sorted(tuple(x)[: len(r.keys) + 2] for x in r.to_df().collect())


def test_parser():
    p = parse("""
    # comment
    watch(Z) :- watch(Y), past[0,30] stake(X, Y, P), not exempt(Z), P > 10.5, Z != Y.
    longterm(X, 'a b') :- alwayspast[0,90] past(0,30] investor(X, _).
    s(X) :- (a(X) since[0,inf] b(X)), V = X + 1, V < 3.
    t(S, T) :- stake(C, S, P), T = msum(P, <C>), T > 100.
    :- watch(X), exempt(X).
    base(acme, 3).
    """)
    r = p.rules[0]
    assert r.head.terms == (Var("Z"),) and len(r.literals) == 3 and r.literals[1].ops == (("past", Range(0, 30)),) and r.literals[2].negated
    assert [type(c) for c in r.conditions] == [Compare, Compare]
    assert p.rules[1].literals[0].ops == (("past", Range(0, 30, True, False)), ("alwayspast", Range(0, 90))) and p.rules[1].head.terms[1] == "a b"
    assert p.rules[2].literals[0].binary == "since" and p.rules[2].literals[0].range == Range(0, None) and isinstance(p.rules[2].conditions[0], Assign)
    assert p.rules[3].conditions[0].contributors == ("C",)
    assert p.rules[4].head is None and p.rules[5].head.terms == ("acme", 3)
    for bad in ("p(X) :- q(X)", "p(X) :- past[3,1] q(X).", "P(x) :- q(x).", "p(X) :- q(X) r(X).", "p(X) :- past[-1,2] q(X)."):
        with pytest.raises(RuleError):
            parse(bad)


@pytest.mark.parametrize("bad", ["p(X, Y) :- q(X).", "p(X) :- q(X), not r(Y).", "p(X) :- q(X), Y > 3.", "p(X) :- q(X, X). s(X) :- q(X).", "p(X) :- q(X), not p(X).", "p(T) :- q(X), p(X), T = sum(X).", "p(V) :- q(X), V = W + 1."])
def test_validation(bad):
    with pytest.raises(RuleError):
        validate(parse(bad))


def test_analysis():
    p = parse("a(X) :- b(X). c(X) :- a(X), not d(X). d(X) :- past[1,2] d(X). d(X) :- b(X). e(X) :- past[30,30] e(X). e(X) :- b(X).")
    level = analysis.strata(p)
    assert level["c"] == level["d"] + 1 and level["a"] == 1
    assert analysis.recursive_groups(p) == [["d"], ["e"]]
    kind = lambda t: analysis.model_kind(parse(t))
    assert kind("a(X) :- b(X). t(X, Z) :- t(X, Y), e(Y, Z).") == "finite"
    assert kind("d(X) :- past[1,2] d(X).") == "constant"
    assert kind("e(X) :- b(X). e(X) :- past[30,30] e(X).") == "periodic"
    assert analysis.pattern_length(parse("e(X) :- past[30,30] e(X).")) == 30
    assert analysis.pattern_length(parse("e(X) :- past[4,4] f(X). f(X) :- past[6,6] e(X). g(X) :- past[4,4] g(X).")) == 20
    f = analysis.classify(parse("a(X) :- past[0,1] b(X)."))
    assert f.forward and not f.backward and f.linear and f.core and f.diamond_past_only
    assert analysis.classify(parse("a(X) :- alwaysfuture[0,1] b(X).")).backward
    assert not analysis.classify(parse("a(X) :- a(Y), a(Z), e(X, Y, Z).")).linear


def test_rewriting(spark):
    text = "a(X) :- past[0,3] b(X). c(X) :- alwayspast[0,5] a(X), not d(X), past[1,2] e(X), X > 0."
    facts = {"b": rel(spark, [(1, 0, 4), (1, 7, 12), (2, 0, 1)], "k"), "d": rel(spark, [(1, 8, 9)], "k"), "e": rel(spark, [(1, 0, 20)], "k")}
    whole = got(Engine(text, facts, Options(fuse=False)).query("c"))
    assert whole and whole == got(Engine(canonicalise(parse(text)), facts, Options(fuse=False)).query("c")) == got(Engine(text, facts).query("c"))
    assert all(len(r.literals) <= 2 and all(len(x.ops) <= 1 for x in r.literals) for r in canonicalise(parse(text)).rules)
    fused = fuse_chains(parse(text))
    assert len(fused.rules) == 1 and fused.rules[0].literals[0].ops == (("past", Range(0, 3)), ("alwayspast", Range(0, 5)))
    x = simplify(parse("p(X) :- top() since[1,2] q(X).").rules[0].literals[0])
    assert x.ops == (("past", Range(1, 2)),) and x.atom.predicate == "q"


OWN = "watch(Z) :- seed(Z). watch(Z) :- watch(Y), past[0,3] big(X, Y), linked(X, Z), Z != Y, not exempt(Z)."


def test_variants_agree(spark):
    rng = random.Random(1)
    many = lambda n, *hi: [(*(rng.randrange(h) for h in hi), s := rng.randrange(40), s + 1 + rng.randrange(9)) for _ in range(n)]
    facts = {"seed": rel(spark, [(0, 0, 40)], "z"), "big": rel(spark, many(90, 5, 9), "x", "y"), "linked": rel(spark, many(120, 5, 9), "x", "y"), "exempt": rel(spark, [(3, 5, 20)], "z")}
    results = []
    for o in (Options(), Options(strategy="naive"), Options(placement="always"), Options(placement="earliest", fuse=False)):
        e = Engine(OWN, facts, o)
        results.append(got(e.query("watch")))
        assert e.report.rounds["watch"][-1] == 0
    assert all(r == results[0] for r in results) and len(results[0]) > 3
    assert results[0] == got(baselines.naive_fixpoint(OWN, facts, "watch")) == got(baselines.seminaive_fixpoint(OWN, facts, "watch"))
    box = placements("w(X) :- alwayspast[0,4] past[0,2] held(X).", {"held": facts["big"].select(x="x")}, "w")
    assert len({str(got(r)) for r in box.values()}) == 1


def test_recursion_with_boxes_and_monotonic_aggregates(spark):
    text = "r(X) :- s(X). r(Y) :- alwayspast[0,2] r(X), e(X, Y)."
    facts = {"s": rel(spark, [(1, 0, 10)], "x"), "e": rel(spark, [(1, 2, 0, 50), (2, 3, 0, 50)], "x", "y")}
    assert got(Engine(text, facts).query("r")) == [(1, 0, 10), (2, 2, 10), (3, 4, 10)]
    control = "c(X, Y) :- own(X, Y, W), T = msum(W, <X>), T > 50. c(X, Z) :- c(X, Y), own(Y, Z, W), T = msum(W, <Y>), T > 50."
    own = rel(spark, [("a", "b", 60, 0, 10), ("b", "c", 60, 5, 10), ("b", "d", 40, 0, 10)], "x", "y", "w")
    assert got(Engine(control, {"own": own}).query("c")) == [("a", "b", 0, 10), ("a", "c", 5, 10), ("b", "c", 5, 10)]


def test_queries_constraints_and_explanations(spark):
    e = Engine("w(X) :- past[0,2] s(X). :- w(X), bad(X).", {"s": rel(spark, [(1, 0, 4)], "x"), "bad": rel(spark, [(1, 5, 9)], "x")})
    assert got(e.query("w", ["who"], between=(3, 100))) == [(1, 3, 6)]
    (text, found), = e.violations()
    assert got(found) == [(1, 5, 6)]
    why = e.explain("w", (1,), 5)
    assert why and "past" in why[0]["rule"] and why[0]["X"] == 1
    with pytest.raises(RuleError):
        Engine("w(X) :- unknown(X).", {"s": rel(spark, [(1, 0, 4)], "x")}).query("w")
    assert got(to_temporal(to_plain(rel(spark, [(1, 0, 4)], "x")), ["x"], "t_start", "t_end")) == [(1, 0, 4)]


def test_since_in_rules(spark):
    facts = {"open": rel(spark, [(1, 0, 9)], "x"), "ask": rel(spark, [(1, 3, 4)], "x")}
    assert got(Engine("w(X) :- open(X) since[0,3] ask(X).", facts).query("w")) == [(1, 3, 7)]


def test_unending_programs(spark):
    s = {"s": points(spark.createDataFrame([(1, 5)], "x long, t long"), ["x"], "t")}
    e = Engine("p(X) :- s(X). p(X) :- past[1,2] p(X).", s)
    assert e.report.kind == "constant" and got(e.query("p")) == [(1, 5, 5), (1, 6, None)]
    e = Engine("p(X) :- s(X). p(X) :- past[30,30] p(X).", s).run()
    assert e.report.kind == "periodic" and e.patterns["p"].period == 60
    assert got(e.query("p", between=(60, 100))) == [(1, 65, 65), (1, 95, 95)]
    e = Engine("p(X) :- s(X). p(X) :- past[1,1] q(X). q(X) :- past[2,2] p(X). q(X) :- z(X).", {**s, "z": rel(spark, [(2, 0, 1)], "x")}).run()
    assert e.patterns["p"].period == 6 and not e.report.clipped
    assert got(e.query("p", between=(31, 42))) == [(1, 32, 32), (1, 35, 35), (1, 38, 38), (1, 41, 41), (2, 31, 32), (2, 34, 35), (2, 37, 38), (2, 40, 41)]
    e = Engine("p(X) :- s(X). p(X) :- past[1,2] q(X). q(X) :- past[1,1] p(X). q(X) :- z(X).", {**s, "z": s["s"].where("x < 0")}).run()
    assert e.report.kind in ("constant", "periodic") and got(e.query("p"))[-1][2] is None and got(e.query("p"))[0] == (1, 5, 5)
    with pytest.raises(RuleError):
        Engine("p(X) :- s(X). p(X) :- past[1,1] q(X), always(X). q(X) :- past[1,1] p(X). q(X) :- z(X).", {**s, "z": s["s"].where("x < 0"), "always": timeless(spark.createDataFrame([(1,)], "x long"), ["x"])}, Options(max_rounds=4)).query("p")
    clipped = Engine("p(X) :- s(X). p(X) :- past[3,3] q(X). q(X) :- past[1,1] p(X). q(X) :- z(X).", {**s, "z": s["s"].where("x < 0")}, Options(horizon=(0, 40)))
    assert [r[1] for r in got(clipped.query("p"))] == [5, 9, 13, 17] and clipped.report.clipped
    repeat = recognise(clipped.query("p").df, ["c0"], 8)
    assert [tuple(x) for x in repeat.collect()] == [(1, 10, 10)]


def test_acceleration_by_rounds(spark):
    rng = random.Random(3)
    for _ in range(6):
        a = rng.randrange(3)
        rng_ = Range(a, a + 1 + rng.randrange(3), rng.random() < 0.5, rng.random() < 0.5)
        lo = rng.randrange(8)
        r = TemporalRelation(spark.createDataFrame([("k", lo, lo + rng.randrange(4))], f"k string, {LO} long, {HI} long"), ("k",))
        fast = accelerate_constant(r, rng_)
        slow, cells = r, set()
        for _ in range(14):
            slow = merge.coalesce(slow.with_df(r.df.unionByName(unary.sometime_past(slow, rng_).df)))
            slow = slow.with_df(spark.createDataFrame(slow.df.collect(), slow.df.schema), coalesced=True)
        want = {c for x in slow.df.collect() for c in range(x[LO], x[HI] + 1) if c < lo + 14}
        have = {c for x in fast.df.collect() for c in range(x[LO], min(x[HI], 200) + 1) if c < lo + 14}
        assert have == want, (rng_, lo)


def test_pattern_joins(spark):
    report = PatternRelation(relation(spark.createDataFrame([(0, 1)], "s long, e long"), [], "s", "e", end_open=False), 60)
    price = relation(spark.createDataFrame([("p", 120, 121), ("q", 50, 55)], "k string, s long, e long"), ["k"], "s", "e", end_open=False)
    assert got(pattern_join(report, price, [])) == [("p", 120, 121)]
    rng = random.Random(4)
    mk = lambda n, p: PatternRelation(TemporalRelation(spark.createDataFrame([(k, a := rng.randrange(20), a + rng.randrange(5)) for k in (1, 1, 2)], f"k long, {LO} long, {HI} long"), ("k",)), p, rng.randrange(2))
    a, b = mk(2, 12), mk(2, 18)
    cells = lambda r, lo, hi: {(x.k, c) for x in r.df.collect() for c in range(max(lo, x[LO]), min(hi, x[HI]) + 1)}
    both = pattern_pattern_join(a, b, ["k"])
    assert both.period == 36
    lo, hi = 200, 400
    assert cells(both.unroll(lo, hi), lo, hi) == cells(a.unroll(lo, hi), lo, hi) & cells(b.unroll(lo, hi), lo, hi)
    with pytest.raises(ValueError):
        pattern_pattern_join(mk(1, 1_000_003), mk(1, 999_983), ["k"])


def test_indexed_probing_equals_hash_join(spark):
    left = [(("a", i % 3), i, i + 4) for i in range(20)]
    right = [((i % 3, "b"), i, i + 2) for i in range(0, 20, 2)]
    out = list(baselines.indexed_probe_join(left, right, lambda p: p[1], lambda q: q[0]))
    want = [(p, q, max(a, c), min(b, d)) for p, a, b in left for q, c, d in right if p[1] == q[0] and max(a, c) <= min(b, d)]
    assert sorted(out) == sorted(want)
    l = TemporalRelation(spark.createDataFrame([(i % 3, a, b) for i, (_, a, b) in enumerate(left)], f"k long, {LO} long, {HI} long"), ("k",))
    from temporal_rules.operators.joins import temporal_join

    assert sorted(map(tuple, baselines.nested_loop_join(l, l, ["k"]).collect())) == sorted(map(tuple, temporal_join(l, l, ["k"]).df.collect()))
    for op in unary.OPERATORS:
        cells = {tuple(x) for x in baselines.pointwise(l, op, Range(1, 2)).collect()}
        assert cells == {(x.k, c) for x in unary.OPERATORS[op](l, Range(1, 2)).df.collect() for c in range(x[LO], x[HI] + 1)}


def test_recursive_sums_give_way_to_larger_ones(spark):
    rules = "near(S) :- seed(S). near(S) :- total(S, T), T > 50. total(S, T) :- near(Y), own(Y, S, P), T = msum(P, <Y>)."
    own = rel(spark, [("a", "b", 60, 0, 10), ("a", "c", 30, 0, 10), ("b", "c", 30, 5, 10), ("c", "d", 70, 0, 10)], "y", "x", "p")
    e = Engine(rules, {"seed": rel(spark, [("a", 0, 10)], "z"), "own": own})
    assert [(s, int(t), a, b) for s, t, a, b in got(e.query("total"))] == [("b", 60, 0, 10), ("c", 30, 0, 5), ("c", 60, 5, 10), ("d", 70, 5, 10)]
