"""Logical graphs, merge placements, spans, measures and experiments."""

import random

import pytest

from temporal_rules import measures
from temporal_rules.model import HI, LO, TemporalRelation
from temporal_rules.operators.merge import coalesce
from temporal_rules.plans import planner
from temporal_rules.plans.language import RuleError, parse
from temporal_rules.plans.patterns import PatternRelation, admit
from temporal_rules.plans.runtime import Engine, Options

PROGRAM = """
a(X) :- past[0,3] b(X, _).
a(X) :- c(X).
d(X, Y) :- alwayspast[0,4] a(X), b(X, Y), not c(X), X > 0.
e(X, T) :- b(X, Y), T = count(Y), T > 1.
f(X) :- a(X) since[0,2] c(X).
"""


@pytest.fixture(scope="module")
def facts(spark):
    rng = random.Random(2)
    rows = lambda n: [(rng.randrange(4), rng.randrange(3), s := rng.randrange(60), s + rng.randrange(12)) for _ in range(n)]
    b = spark.createDataFrame(rows(40), f"x long, y long, {LO} long, {HI} long")
    return {"b": TemporalRelation(b, ("x", "y")), "c": TemporalRelation(spark.createDataFrame(rows(6), b.schema).drop("y"), ("x",))}


def got(r):
    return sorted(map(tuple, coalesce(r).df.collect()))


def test_graphs_give_what_the_runtime_gives(spark, facts):
    program = parse(PROGRAM)
    for goal in ("a", "d", "e", "f"):
        want = got(Engine(program, facts, Options(fuse=False)).query(goal))
        assert want
        plans = planner.variants(planner.compile_logical(program, goal))
        for name, plan in plans.items():
            assert got(planner.to_relation(plan, facts)) == want, (goal, name)
        assert got(Engine(program, facts, Options(hints=frozenset({"input", "union"}))).query(goal)) == want
    d = planner.variants(planner.compile_logical(program, "d"))
    merges = {k: sum(n.kind == "Merge" for n in v.walk()) for k, v in d.items()}
    assert merges["minimal"] == 1 and merges["always"] > merges["hinted"] > merges["minimal"] and "Move" in d["minimal"].text()
    stats = {p: planner.sample_stats(r, 1) for p, r in facts.items()}
    name, plan = planner.choose(planner.compile_logical(program, "d"), stats)
    assert got(planner.to_relation(plan, facts)) == got(Engine(program, facts).query("d")) and stats["b"].islands <= stats["b"].rows == 40
    with pytest.raises(RuleError):
        planner.compile_logical(parse("p(X) :- q(X). p(X) :- past[1,2] p(X)."), "p")


def test_spans_reach_the_inputs(spark, facts, tmp_path):
    program = parse(PROGRAM)
    spans = planner.input_span(program, "d", (10, 20))
    assert spans["b"] == (3, 20)
    for goal in ("a", "d", "f"):
        e = Engine(program, facts)
        assert got(e.query_span(goal, (10, 20))) == got(e.query(goal, between=(10, 20)))
    assert planner.input_span(parse("p(X) :- q(X). p(X) :- past[1,2] p(X)."), "p", (0, 9))["q"] == (None, None)
    path = str(tmp_path / "b")
    facts["b"].df.write.parquet(path)
    stored = planner.within_span(facts["b"].with_df(spark.read.parquet(path)), (3, 20))
    plan = stored.df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(__lo), IsNotNull(__hi), LessThanOrEqual(__lo,41), GreaterThanOrEqual(__hi,5)]" in plan


def test_plans_have_no_cartesian_product_and_few_exchanges(spark, sf):
    from temporal_rules.workloads.queries import QUERIES

    for name in ("investor_longterm", "temporal_join", "temporal_minus", "own_new_owner", "agg_instant_sum", "matinee"):
        counts = measures.plan_counts(QUERIES[name](spark, sf))
        assert not counts["CartesianProduct"] and not counts["BroadcastNestedLoopJoin"], name
    assert measures.growth([(1, 2.0), (10, 20.0), (100, 200.0)]) == pytest.approx(1)
    m = measures.elapsed(lambda: spark.range(10), 2)
    assert m["runs"] == 2 and not m["censored"] and measures.speed_up(8, 2) == 4


def test_patterns_reject_what_they_say(spark):
    base = TemporalRelation(spark.createDataFrame([("a", 0, 3)], f"k string, {LO} long, {HI} long"), ("k",))
    new = TemporalRelation(spark.createDataFrame([("a", 20, 23), ("a", 42, 45), ("b", 0, 1)], base.df.schema), ("k",))
    assert got(admit(new, PatternRelation(base, 10))) == [("a", 44, 45), ("b", 0, 1)]
    assert got(admit(new.where("k = 'z'"), PatternRelation(base, 10))) == []


def test_experiments_run(spark, sf):
    from temporal_rules.workloads import experiments

    for name in ("merging", "joining", "averages", "stations", "hierarchy"):
        rows = list(experiments.FAMILIES[name](spark, sf))
        assert rows and all(len(r) == 6 for r in rows)
    small = [r for r in experiments.generator(spark, sf, (1_000,))]
    assert len(small) == 4 and all(r[4] > 0 for r in small)
