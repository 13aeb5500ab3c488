"""Every method, variant and workload as a query over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import timeseries as ts
from ..model import HI, LO, MICROS, STEPS, Range, TemporalRelation, points, relation, timeless
from ..operators import aggregates as ag
from ..operators import binary, joins, merge, unary
from ..plans.patterns import PatternRelation, pattern_join
from ..plans.runtime import Engine, Options
from . import base as b

QUERIES = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def plain(r: TemporalRelation) -> DataFrame:
    return merge.coalesce(r).to_df(flags=False)


def flagged(r: TemporalRelation) -> DataFrame:
    return merge.coalesce(r).to_df()


# Rules of the entry query: stakes with pauses of up to 30 days count as lasting, for 90 days at least.
INVESTOR = """
investor(X, Y) :- stake(X, Y, P).
longterm(X, Y) :- alwayspast[0,90] past[0,30] investor(X, Y).
"""


@query
def investor_longterm(spark: SparkSession, sf: str) -> DataFrame:
    return Engine(INVESTOR, {"stake": b.stake(spark, sf)}).query("longterm", ["cust", "supp"]).to_df(flags=False)


# Unary operators on big stakes by supplier.
@query
def op_past_sometime(spark, sf):
    return plain(unary.sometime_past(b.big_by_supp(spark, sf), Range(2, 5)))


@query
def op_future_sometime(spark, sf):
    return plain(unary.sometime_future(b.big_by_supp(spark, sf), Range(2, 5)))


@query
def op_past_always(spark, sf):
    return plain(unary.always_past(b.big_by_supp(spark, sf), Range(3, 12)))


@query
def op_future_always(spark, sf):
    return plain(unary.always_future(b.big_by_supp(spark, sf), Range(3, 12)))


@query
def op_shift(spark, sf):
    return plain(unary.shift(b.big_by_supp(spark, sf), 7))


@query
def op_generic_t(spark, sf):
    return plain(unary.shift_ends(merge.coalesce(b.big_by_supp(spark, sf)), unary.Transform(-4, 9)))


@query
def op_bracket_mix(spark, sf):
    return flagged(unary.sometime_past(b.big_by_supp(spark, sf), Range(0, 3, True, False)))


def _chain(ops, how):
    return lambda spark, sf: plain(unary.apply_chain(b.big_by_supp(spark, sf), list(ops), **how))


CHAINS = {
    "chain_diamond_diamond": ((("past", Range(1, 4)), ("future", Range(2, 3))), {}),
    "chain_box_box": ((("alwayspast", Range(0, 4)), ("alwaysfuture", Range(0, 6))), {}),
    "chain_box_diamond": ((("past", Range(0, 10)), ("alwayspast", Range(0, 40))), {}),
    "chain_diamond_box": ((("alwayspast", Range(0, 20)), ("past", Range(0, 15))), {}),
    "chain_box_diamond_earliest": ((("past", Range(0, 10)), ("alwayspast", Range(0, 40))), {"placement": "earliest"}),
    "chain_box_diamond_unfused": ((("past", Range(0, 10)), ("alwayspast", Range(0, 40))), {"placement": "always", "fuse": False}),
}
for _n, (_ops, _how) in CHAINS.items():
    QUERIES[_n] = _chain(_ops, _how)


@query
def coalesce_stake(spark, sf):
    return plain(b.pairs(spark, sf, 0))


@query
def coalesce_gap(spark, sf):
    return merge.coalesce(b.big_by_supp(spark, sf), gap=20).to_df(flags=False)


@query
def merge_hotkey(spark, sf):
    r = b.stake(spark, sf, b.BIG)
    hot = r.with_df(r.df.select(F.pmod("supp", F.lit(2)).alias("half"), LO, HI), ["half"])
    return merge.coalesce_hot(hot, 200).to_df(flags=False)


@query
def merge_streaming(spark, sf):
    """Every state that the streaming strategy forwards, facts arriving by price: partial results and what subsumes them."""
    r = b.stake(spark, sf, b.BIG)
    return merge.stream_states(_by_price(r, ["supp"]), "seq").to_df(flags=False)


def _by_price(r: TemporalRelation, keys: list[str]) -> TemporalRelation:
    # Dealt by key once: the groups and the order then need no further exchange.
    seen = r.df.repartition(*keys).groupBy(*keys, LO, HI).agg(F.min("price").alias("price"))
    order = Window.partitionBy(*keys).orderBy("price", LO, HI)
    return r.with_df(seen.select(*keys, LO, HI, F.row_number().over(order).alias("seq")), keys)


# The same operators over every stake, by customer and supplier: by supplier alone most days would be covered.
def _whole(f):
    return lambda spark, sf: f(b.pairs(spark, sf, 0))


_ALL = {
    "op_past_sometime": lambda r: plain(unary.sometime_past(r, Range(2, 5))),
    "op_future_sometime": lambda r: plain(unary.sometime_future(r, Range(2, 5))),
    "op_past_always": lambda r: plain(unary.always_past(r, Range(3, 12))),
    "op_future_always": lambda r: plain(unary.always_future(r, Range(3, 12))),
    "op_shift": lambda r: plain(unary.shift(r, 7)),
    "op_generic_t": lambda r: plain(unary.shift_ends(merge.coalesce(r), unary.Transform(-4, 9))),
    "op_bracket_mix": lambda r: flagged(unary.sometime_past(r, Range(0, 3, True, False))),
    "coalesce_gap": lambda r: merge.coalesce(r, gap=20).to_df(flags=False),
    "merge_hotkey": lambda r: merge.coalesce_hot(r.with_df(r.df.select(F.pmod("supp", F.lit(2)).alias("half"), LO, HI), ["half"]), 200).to_df(flags=False),
    "lift_month": lambda r: ag.lift_to_unit(r, "month").to_df(flags=False),
    "covered_time": lambda r: ag.covered_time(r, ["cust", "supp"]),
}
for _n, (_ops, _how) in CHAINS.items():
    _ALL[_n] = lambda r, ops=_ops, how=_how: plain(unary.apply_chain(r, list(ops), **how))
for _n, _g in _ALL.items():
    QUERIES[f"{_n}_all"] = _whole(_g)


@query
def merge_streaming_all(spark, sf):
    r = b.stake(spark, sf)
    return merge.stream_states(_by_price(r, ["cust", "supp"]), "seq").to_df(flags=False)


@query
def session_events(spark, sf):
    e = b.table(spark, sf, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    g = e.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.unix_micros("w.start").alias("t_start"), F.unix_micros("w.end").alias("t_end"), "n")


# Joins and negation.
def _two(spark, sf):
    r = b.big(spark, sf)
    return r.select(c1="cust", supp="supp"), r.select(c2="cust", supp="supp")


@query
def temporal_join(spark, sf):
    l, r = _two(spark, sf)
    got = joins.temporal_join(l, r, ["supp"])
    return plain(got.where("c1 < c2"))


@query
def temporal_join3(spark, sf):
    l, r = _two(spark, sf)
    got = joins.temporal_join_all([l, r, b.exempt(spark, sf)], [["supp"], ["supp"]])
    return plain(got.where("c1 < c2"))


def _windows(spark, sf) -> TemporalRelation:
    """A window a day, from 2024 on, to the day after the last event."""
    last = b.table(spark, sf, "events").agg(F.max(F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")))).first()[0]
    w = spark.range((last or 0) + 2).select((F.col("id") * 24 * b.HOUR + 14 * b.HOUR + 1704067200000000).alias("s"), (F.col("id") * 24 * b.HOUR + 16 * b.HOUR + 1704067200000000).alias("e"), F.col("id").alias("day"))
    return relation(w, ["day"], "s", "e", MICROS)


@query
def matinee(spark, sf):
    e = b.table(spark, sf, "events").where("event_type = 'click'").select("event_id", "user_id", F.expr("unix_micros(cast(ts as timestamp))").alias("at"))
    goes = relation(e, ["event_id", "user_id"], F.col("at"), F.col("at") + 2 * b.HOUR, MICROS)
    return joins.temporal_join(goes, _windows(spark, sf), []).to_df(flags=False)


@query
def temporal_join_theta(spark, sf):
    l = b.big_by_supp(spark, sf)
    s = b.table(spark, sf, "supplier").select(F.col("s_suppkey").alias("other"), (F.col("s_suppkey") * 17 % 2000).alias("s"))
    # Both sides are coalesced, so the result is too and is not exchanged again: it is far larger than they are.
    return plain(joins.temporal_join(merge.coalesce(l), merge.coalesce(relation(s, ["other"], F.col("s"), F.col("s") + 25)), []))


@query
def temporal_semi(spark, sf):
    return plain(joins.temporal_semi(b.big(spark, sf), b.exempt(spark, sf), ["supp"]))


@query
def temporal_minus(spark, sf):
    return plain(joins.temporal_minus(b.linked(spark, sf), b.big(spark, sf), ["cust", "supp"]))


@query
def interval_union(spark, sf):
    return plain(joins.interval_union(b.big_by_supp(spark, sf), b.exempt(spark, sf)))


@query
def interval_intersect(spark, sf):
    return plain(joins.interval_intersect(b.big_by_supp(spark, sf), b.exempt(spark, sf)))


@query
def interval_except(spark, sf):
    return plain(joins.interval_except(b.exempt(spark, sf), b.big_by_supp(spark, sf)))


@query
def own_new_owner(spark, sf):
    rule = "owner(X, Y) :- alwaysfuture[0,1] big(X, Y), not past(0,1] big(X, Y)."
    return Engine(rule, {"big": b.big(spark, sf)}).query("owner", ["cust", "supp"]).to_df()


# Since and until.
@query
def conv_since(spark, sf):
    return plain(binary.since(b.said(spark, sf, "assistant"), b.said(spark, sf, "user"), Range(0, 3), ["conv_id"]))


@query
def conv_until(spark, sf):
    return plain(binary.until(b.said(spark, sf, "assistant"), b.said(spark, sf, "user"), Range(1, 3), ["conv_id"]))


def _calm(spark, sf):
    h = b.hourly(spark, sf)
    w = Window.partitionBy("user_id").orderBy("h")
    # A last reading counts for a day.
    hours = h.groupBy("user_id", "h").agg(F.max("value").alias("v")).withColumn("n", F.coalesce(F.lead("h").over(w), F.col("h") + 24))
    calm = relation(hours.where("v < 150"), ["user_id"], "h", "n", b.HOURS)
    return calm, points(h.where("event_type = 'signup'").select("user_id", "h").distinct(), ["user_id"], "h", b.HOURS)


@query
def ev_since(spark, sf):
    a, s = _calm(spark, sf)
    return flagged(binary.since(a, s, Range(0, 12), ["user_id"]))


@query
def ev_until(spark, sf):
    a, s = _calm(spark, sf)
    return flagged(binary.until(a, s, Range(0, 12), ["user_id"]))


# Aggregation.
def _instant(f):
    def run(spark, sf):
        r = ag.agg_at_each_time(b.stake(spark, sf), ["supp"], f, "price")
        return r.with_df(r.df.withColumn("value", F.round(F.col("value").cast("double"), 2)), coalesced=True).to_df(flags=False)

    return run


for _f in ("sum", "count", "max", "min"):
    QUERIES[f"agg_instant_{_f}"] = _instant(_f)


@query
def agg_history(spark, sf):
    r = merge.coalesce(b.stake(spark, sf))
    return ag.agg_across_time(r, ["supp"], facts=F.count(F.lit(1)), dearest=F.max("price"), buyers=F.count_distinct("cust"))


@query
def agg_monotonic(spark, sf):
    r = ag.monotonic(b.stake(spark, sf), ["supp"], "msum", "price", ["cust"])
    return r.with_df(r.df.withColumn("value", F.round(F.col("value").cast("double"), 2)), coalesced=True).to_df(flags=False)


@query
def lift_month(spark, sf):
    return ag.lift_to_unit(b.big_by_supp(spark, sf), "month").to_df(flags=False)


@query
def rollup_units(spark, sf):
    o = b.table(spark, sf, "orders")
    got = ag.rollup_units(o, F.col("o_orderdate").cast("date"), F.col("o_totalprice").cast("decimal(18,2)"))
    return got.select("y", "m", F.col("total").cast("double").alias("total"), "n")


@query
def covered_time(spark, sf):
    return ag.covered_time(b.big_by_supp(spark, sf), ["supp"])


# Ownership: recursion with sometime, always, negation and aggregation.
def _own(rule: str, options: Options = Options()):
    def run(spark, sf):
        make = {"seed": b.seed, "big": b.big, "linked": b.linked, "stake": b.stake, "held": lambda *at: b.pairs(*at, 0), "exempt": b.exempt}
        facts = {p: f(spark, sf) for p, f in make.items() if p == "seed" or f" {p}(" in rule}
        return Engine("watch(Z) :- seed(Z).\n" + rule, facts, options).query("watch", ["supp"]).to_df(flags=False)

    return run


OWN_TEMPORAL = "watch(Z) :- watch(Y), past[0,30] stake(X, Y, P), P > 94700, linked(X, Z), Z != Y."
OWN_NEGATION = "watch(Z) :- watch(Y), past[0,30] stake(X, Y, P), P > 94700, linked(X, Z), Z != Y, not exempt(Z)."
OWN_DIAMOND = "watch(Z) :- watch(Y), past[0,30] big(X, Y), linked(X, Z)."
OWN_BOX = "watch(Z) :- watch(Y), alwayspast[0,20] held(X, Y), linked(X, Z)."
QUERIES["own_temporal"] = _own(OWN_TEMPORAL)
QUERIES["own_temporal_naive"] = _own(OWN_TEMPORAL, Options(strategy="naive"))
QUERIES["own_negation"] = _own(OWN_NEGATION)
QUERIES["own_diamond"] = _own(OWN_DIAMOND)
for _p in ("minimal", "earliest", "always"):
    QUERIES[f"own_box_{_p}"] = _own(OWN_BOX, Options(placement=_p))


# A box over a diamond: three plans for the three placements of the merge.
OWN_WIDE = "watch(Z) :- watch(Y), alwayspast[0,40] past[0,10] held(X, Y), linked(X, Z)."
for _p in ("minimal", "earliest", "always", "auto"):
    QUERIES[f"own_wide_{_p}"] = _own(OWN_WIDE, Options(placement=_p))


@query
def own_aggregation(spark, sf):
    rule = "heavy(S) :- stake(C, S, P), T = sum(P), T > 400000."
    return Engine(rule, {"stake": b.stake(spark, sf)}).query("heavy", ["supp"]).to_df(flags=False)


# Hierarchy.
HIER = """
activeCust(C) :- past[0,30] placed(C, O).
steady(C) :- alwayspast[0,60] activeCust(C).
inRegion(C, R) :- lives(C, N), partOf(N, R).
notable(C) :- steady(C).
notable(C) :- big(C, S).
hot(R) :- notable(C), inRegion(C, R), steady(C).
"""


def _hier_facts(spark, sf):
    c = b.table(spark, sf, "customer").select(F.col("c_custkey").alias("cust"), F.col("c_nationkey").cast("long").alias("nation"))
    n = b.table(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("nation"), F.col("n_regionkey").cast("long").alias("region"))
    return {"placed": b.placed(spark, sf), "lives": timeless(c, ["cust", "nation"]), "partOf": timeless(n, ["nation", "region"]), "big": b.big(spark, sf)}


@query
def hier_nonrec(spark, sf):
    """All six rules, up to the regions."""
    return Engine(HIER, _hier_facts(spark, sf)).query("hot", ["region"]).to_df()


@query
def hier_steady(spark, sf):
    return Engine(HIER, _hier_facts(spark, sf)).query("steady", ["cust"]).to_df()


@query
def hier_rec(spark, sf):
    """Membership over customer, nation and region, all timeless, by recursion."""
    c = b.table(spark, sf, "customer").select(F.concat(F.lit("c"), "c_custkey").alias("x"), F.concat(F.lit("n"), "c_nationkey").alias("y"))
    n = b.table(spark, sf, "nation").select(F.concat(F.lit("n"), "n_nationkey").alias("x"), F.concat(F.lit("r"), "n_regionkey").alias("y"))
    rules = "memberof(X, Y) :- within(X, Y). memberof(X, Z) :- memberof(X, Y), within(Y, Z)."
    return Engine(rules, {"within": timeless(c.unionByName(n), ["x", "y"])}).query("memberof", ["x", "y"]).to_df()


@query
def hier_affected(spark, sf):
    """Trouble spreads with a delay among customers who hold big stakes of one supplier at a time."""
    o = b.table(spark, sf, "orders").where("o_orderpriority = '1-URGENT' and o_totalprice > 400000").select(F.col("o_custkey").alias("cust"), b.day("o_orderdate").alias("d"))
    rules = """
    same(C, D) :- big(C, S), big(D, S), C != D.
    affected(C) :- urgent(C).
    affected(C) :- past[1,7] affected(D), same(C, D).
    """
    facts = {"big": b.big(spark, sf), "urgent": relation(o, ["cust"], F.col("d"), F.col("d") + 1)}
    return Engine(rules, facts).query("affected", ["cust"]).to_df(flags=False)


# Stations.
@query
def meteo_heat(spark, sf):
    rules = f"above(U) :- reading(U, V), V > 50. high(U) :- alwayspast[0,{6 * b.HOUR}] above(U)."
    return Engine(rules, {"reading": b.reading(spark, sf)}).query("high", ["user_id"]).to_df(flags=False)


@query
def meteo_wind(spark, sf):
    rules = f"""
    strong(U) :- reading(U, V), V > 110.
    quiet(U) :- reading(U, V), V < 5.
    gust(U) :- past[0,{24 * b.HOUR}] strong(U), not quiet(U).
    """
    return Engine(rules, {"reading": b.reading(spark, sf)}).query("gust", ["user_id"]).to_df(flags=False)


# The generator's programs, on stakes of a customer and supplier.
@query
def gen_box(spark, sf):
    return plain(unary.always_past(b.pairs(spark, sf, 0), Range(0, 30)))


@query
def gen_diamond(spark, sf):
    return plain(unary.sometime_past(b.pairs(spark, sf, 0), Range(0, 30)))


@query
def gen_union(spark, sf):
    rules = "both(X, Y) :- a(X, Y). both(X, Y) :- b(X, Y)."
    facts = {"a": b.big(spark, sf), "b": unary.shift(b.linked(spark, sf), 5)}
    return Engine(rules, facts).query("both", ["cust", "supp"]).to_df(flags=False)


@query
def gen_intersection(spark, sf):
    rules = "both(X, Y) :- a(X, Y), b(X, Y)."
    facts = {"a": b.big(spark, sf), "b": unary.shift(b.linked(spark, sf), 5)}
    return Engine(rules, facts).query("both", ["cust", "supp"]).to_df(flags=False)


def generated(spark, n: int, program: str, seed: int = 1) -> DataFrame:
    """The generator's programs on n synthetic facts (bench)."""
    r = b.generate_facts(spark, n, max(1, n // 20), 2_000, seed)
    if program == "box":
        return plain(unary.always_past(r, Range(0, 10)))
    if program == "diamond":
        return plain(unary.sometime_past(r, Range(0, 10)))
    s = b.generate_facts(spark, n, max(1, n // 20), 2_000, seed + 1)
    return plain(joins.interval_union(r, s) if program == "union" else joins.interval_intersect(r, s))


# Patterns.
def _shipped(spark, sf):
    """Shipped value by day, and its 90 % quantile as a timeless fact."""
    d = b.table(spark, sf, "lineitem").groupBy(b.day("l_shipdate").alias("d")).agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    first = relation(spark.range(1).select(F.lit(0).alias("s"), F.lit(1).alias("e"), F.lit(1).alias("kind")), ["kind"], "s", "e", end_open=False)
    return {"change": points(d, ["d", "v"], "d"), "usual": timeless(d.agg(F.percentile("v", F.lit(0.9)).alias("k")), ["k"]), "first": first}


# A report every 30 days, lasting a day; days of very high shipments that follow one by at most two days.
REPORT = """
report(K) :- first(K).
report(K) :- past[30,30] report(K).
event(D) :- change(D, V), usual(U), V > U.
"""


@query
def report_cause(spark, sf):
    rules = REPORT + "cause(D, K) :- event(D), past[0,2] report(K)."
    return Engine(rules, _shipped(spark, sf)).query("cause", ["d", "kind"]).to_df()


@query
def pattern_minus_rules(spark, sf):
    """High days that no report explains: negation over facts that repeat for ever."""
    rules = REPORT + "other(D) :- event(D), not past[0,2] report(K2)."
    return Engine(rules.replace("K2", "_"), _shipped(spark, sf)).query("other", ["d"]).to_df()


@query
def pattern_rules(spark, sf):
    """Two patterns joined, and an always-operator over one: the answers repeat for ever and are shown for 400 days."""
    rules = REPORT + """
    audit(K) :- first(K).
    audit(K) :- past[7,7] audit(K).
    both(K) :- report(K), past[0,1] audit(K).
    lasting(K) :- alwayspast[0,1] past[0,3] report(K).
    busy(K) :- both(K).
    busy(K) :- lasting(K).
    """
    facts = {"first": _shipped(spark, sf)["first"], "change": _shipped(spark, sf)["change"], "usual": _shipped(spark, sf)["usual"]}
    return Engine(rules, facts).query("busy", ["kind"], between=(0, 400)).to_df()


@query
def pattern_answer(spark, sf):
    """The unbounded answer: rows that hold once and rows that hold again every so many days."""
    return Engine(REPORT + "soon(K) :- future[1,2] report(K).", _shipped(spark, sf)).query("soon", ["kind"]).to_df()


@query
def weekday_rules(spark, sf):
    """Orders by the weekday that they meet, where every weekday is derived from its first one by a rule."""
    w = relation(spark.range(7).select(F.col("id").alias("dow")), ["dow"], F.col("dow"), F.col("dow") + 1)
    o = b.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority", b.day("o_orderdate").alias("d"))
    rules = "weekday(D) :- first(D). weekday(D) :- past[7,7] weekday(D). on(O, P, D) :- placed(O, P), weekday(D)."
    met = Engine(rules, {"first": w, "placed": points(o, ["o_orderkey", "o_orderpriority"], "d")}).query("on", ["ord", "o_orderpriority", "dow"])
    return met.df.groupBy("dow", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query
def weekday_orders(spark, sf):
    """Orders by the weekday pattern that they meet."""
    w = relation(spark.range(7).select(F.col("id").alias("dow")), ["dow"], F.col("dow"), F.col("dow") + 1)
    o = b.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority", b.day("o_orderdate").alias("d"))
    met = pattern_join(PatternRelation(w, 14), points(o, ["o_orderkey", "o_orderpriority"], "d"), [])
    return met.df.groupBy("dow", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query
def pattern_unroll(spark, sf):
    w = relation(b.table(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("k")), ["k"], F.col("k"), F.col("k") + 2)
    return PatternRelation(w, 2 * 31).unroll(0, 2 * 200 - 1).to_df(flags=False)


@query
def constant_reach(spark, sf):
    e = b.hourly(spark, sf).where("event_type = 'error'").groupBy("user_id").agg(F.min("h").alias("h"))
    rules = "hit(U) :- failed(U). hit(U) :- past[1,2] hit(U)."
    return Engine(rules, {"failed": points(e, ["user_id"], "h", b.HOURS)}).query("hit", ["user_id"]).to_df()


# Series.
def _series(s: ts.Series, digits: int = 2) -> DataFrame:
    return s.df.select(*s.keys, "t", F.round("v", digits).alias("v"))


SERIES = {
    "ts_shift": lambda s: ts.shift(s, 1),
    "ts_rolling": lambda s: ts.rolling(s, 3),
    "ts_rolling_partial": lambda s: ts.rolling(s, 3, "max", partial=True),
    "ts_sma": lambda s: ts.sma(s, 7),
    "ts_ema": lambda s: ts.ema(s, 10),
    "ts_ema_blocks": lambda s: ts.ema_blocks(s, 10, block=100),
    "ts_cma": lambda s: ts.cma(s, 7),
    "ts_cma_even": lambda s: ts.cma(s, 12),
    "ts_stock_to_flow": ts.stock_to_flow,
    "ts_flow_to_stock": ts.flow_to_stock,
    "ts_downsample": lambda s: ts.downsample(s, F.expr("t div 30")),
    "ts_trend": lambda s: ts.decompose(s, 7).trend,
    "ts_detrend": lambda s: ts.decompose(s, 7).detrend,
    "ts_seasonal": lambda s: ts.decompose(s, 7).seasonal,
    "ts_residual": lambda s: ts.decompose(s, 7).residual,
}
#: Digits at which no exact value lies half-way: sums have four decimals, averages of 7 or 12 of them more.
DIGITS = {k: 4 for k in ("ts_shift", "ts_rolling", "ts_rolling_partial", "ts_stock_to_flow", "ts_flow_to_stock")}
DIGITS |= {k: 6 for k in ("ts_sma", "ts_cma", "ts_trend", "ts_detrend")} | {"ts_cma_even": 7}
for _n, _g in SERIES.items():
    QUERIES[_n] = lambda spark, sf, g=_g, digits=DIGITS.get(_n, 2): _series(g(b.daily_revenue(spark, sf)), digits)


@query
def ts_upsample(spark, sf):
    weekly = ts.downsample(b.daily_orders(spark, sf), F.expr("t div 7"), "sum")
    return _series(ts.upsample(weekly.with_df(weekly.df.withColumn("t", F.col("t") * 7))), 4)


@query
def ts_upsample_hold(spark, sf):
    weekly = ts.downsample(b.daily_orders(spark, sf), F.expr("t div 7"), "sum")
    return _series(ts.upsample(weekly.with_df(weekly.df.withColumn("t", F.col("t") * 7)), method="hold"), 4)


@query
def ts_rolling_rules(spark, sf):
    """The rule form of the rolling window, summed."""
    r = ts.rolling_by_rules(b.daily_orders(spark, sf), 3)
    g = r.df.groupBy("priority", F.col(LO).alias("t")).agg(F.sum("v").alias("v"), F.count(F.lit(1)).alias("n")).where("n = 3")
    return g.select("priority", "t", "v")


@query
def ts_ema_rules(spark, sf):
    """The exponential average by its rules: the mean of the first ten points, then a part of the value and a part of
    the average before, summed.  Time is the number of the point, as points are not on every day."""
    s = b.daily_revenue(spark, sf)
    k = ["l_returnflag", "l_linestatus"]
    i = s.df.withColumn("i", F.row_number().over(Window.partitionBy(*k).orderBy("t")).cast("long"))
    first = i.where("i <= 10").groupBy(*k).agg(F.avg("v").alias("v"), F.max("i").alias("i")).where("i = 10")
    rules = """
    part(F, L, Y) :- past[1,1] ema(F, L, X), Y = X * 9 / 11.
    part(F, L, Y) :- later(F, L, V), Y = V * 2 / 11.
    ema(F, L, Y) :- part(F, L, X), Y = sum(X).
    ema(F, L, Y) :- begin(F, L, Y).
    seen(F, L, T, Y) :- ema(F, L, Y), point(F, L, T).
    """
    at = lambda df, *more: points(df, [*k, *more], "i", STEPS)
    facts = {"begin": at(first, "v"), "later": at(i.where("i > 10"), "v"), "point": at(i, "t")}
    got = Engine(rules, facts).query("seen", [*k, "t", "v"])
    return got.df.select(*k, "t", F.round("v", 2).alias("v"))


@query
def ts_upsample_rules(spark, sf):
    """Weekly sums to days by rules: a series of days that never ends, this week's point and the next one's, and the line between."""
    weekly = ts.downsample(b.daily_orders(spark, sf), F.expr("t div 7"), "sum")
    w = weekly.df.select("priority", (F.col("t") * 7).alias("week"), "v")
    rules = """
    day(Y) :- past[1,1] day(X), Y = X + 1.
    day(X) :- origin(X).
    this(C, V, W) :- past[0,7) weekly(C, V, W).
    next(C, V, W) :- future(0,7] weekly(C, V, W).
    finer(C, Z, V) :- day(Z), this(C, A, P), next(C, B, Q), V = A + (B - A) * (Z - P) / (Q - P).
    finer(C, P, V) :- weekly(C, V, P).
    """
    facts = {"weekly": points(w, ["priority", "v", "week"], "week", STEPS), "origin": points(spark.range(1).select(F.lit(0).cast("long").alias("x")), ["x"], "x", STEPS)}
    got = Engine(rules, facts).query("finer", ["priority", "t", "v"])
    return got.df.select("priority", "t", F.round("v", 4).alias("v"))


@query
def ts_frequency(spark, sf):
    return ts.frequency(b.daily_orders(spark, sf))


@query
def ts_add(spark, sf):
    s = b.daily_orders(spark, sf)
    return _series(ts.add(s, ts.shift(s, 1)))


@query
def ts_embedding_sma(spark, sf):
    return _series(ts.sma(b.vector_series(spark, sf), 8), 4)


@query
def ts_event_seasonal(spark, sf):
    return _series(ts.decompose(b.daily_events(spark, sf), 7).seasonal)


# Wrapping and pairwise relations.
@query
def wrap_roundtrip(spark, sf):
    """Plain facts get an interval, join with temporal ones, and become plain again."""
    good = b.table(spark, sf, "labels").where("quality = 1").select(F.col("doc_id").alias("ord"))
    rules = "hit(C, O) :- placed(C, O), good(O)."
    return Engine(rules, {"placed": b.placed(spark, sf), "good": timeless(good, ["ord"])}).query("hit", ["cust", "ord"]).to_df(flags=False)


@query
def wrap_rules(spark, sf):
    """One program in both modes: intervals unwrapped to terms, ids created by a plain rule, intervals wrapped again."""
    rules = """
    spell(C, S, B, E) :- held(C, S) @ (B, E).
    deal(new D, C, S, B, E) :- spell(C, S, B, E), E - B > 45.
    active(D, C) @ (B, E) :- deal(D, C, S, B, E).
    follow(D, C) :- past[0,5] active(D, C).
    """
    return Engine(rules, {"held": b.pairs(spark, sf, 0)}).query("follow", ["deal", "cust"]).to_df(flags=False)


@query
def relations13(spark, sf):
    l, r = _two(spark, sf)
    j = l.df.alias("a").join(r.df.alias("b"), F.col("a.supp") == F.col("b.supp")).where("c1 < c2")
    rel = joins.relation13(F.col(f"a.{LO}"), F.col(f"a.{HI}"), F.col(f"b.{LO}"), F.col(f"b.{HI}"))
    return j.groupBy(rel.alias("relation")).agg(F.count(F.lit(1)).alias("n"))


@query
def hold_readings(spark, sf):
    return b.reading(spark, sf).to_df(flags=False)


@query
def sweep_counts(spark, sf):
    r = merge.coalesce(b.big(spark, sf))
    return joins.sweep(r, ["supp"]).select("supp", F.shiftright(LO, 1).alias("t"), F.col("n").cast("long").alias("n"))


@query
def top_intervals(spark, sf):
    """The three longest islands of each supplier."""
    m = merge.coalesce(b.big_by_supp(spark, sf)).to_df(flags=False)
    w = Window.partitionBy("supp").orderBy(F.desc(F.col("t_end") - F.col("t_start")), "t_start")
    return m.withColumn("rank", F.row_number().over(w)).where("rank <= 3")
