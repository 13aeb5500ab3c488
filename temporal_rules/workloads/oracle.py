"""The queries in DuckDB's SQL, by expansion to days or cells instead of interval arithmetic."""

from __future__ import annotations

DAY = "date_diff('day', date '1995-01-01', {}::date)"
STAKE = f"""stake as (select o_custkey cust, l_suppkey supp, l_extendedprice price, {DAY.format('o_orderdate')} s,
 {DAY.format('o_orderdate')} + l_quantity::bigint e from lineitem join orders on l_orderkey = o_orderkey)"""
BIG = "big as (select cust, supp, s, e from stake where price > 94700)"
LINKED = "linked as (select cust, supp, s, e from stake where price > 53000)"
SEED = "seed as (select s_suppkey supp, 0 s, 2500 e from supplier where s_suppkey % 20 = 0)"
EXEMPT = "exempt as (select s_suppkey supp, 500 s, 1500 e from supplier where s_acctbal < 0)"


def days(name: str, source: str, keys: str, extra: str = "") -> str:
    return f"{name} as (select distinct {keys}, d::bigint d from (select {keys}{extra}, unnest(range(s, e)) d from {source}))"


def cells(name: str, source: str, keys: str) -> str:
    """Half-open facts as cells: points are even, gaps odd."""
    return f"{name} as (select distinct {keys}, d::bigint d from (select {keys}, unnest(range(2 * s, 2 * e)) d from {source}))"


def islands(source: str, keys: str, extra: str = "", last: str = "max(d) + 1") -> str:
    part = f"partition by {keys}" if keys else ""
    k = f"{keys}, " if keys else ""
    return f"select {k}{extra}min(d)::bigint t_start, ({last})::bigint t_end from (select {k}d, d - row_number() over ({part} order by d) g from {source}) group by {k}g"


def cell_islands(source: str, keys: str) -> str:
    return f"""select {keys}, (a >> 1)::bigint t_start, ((z + 1) >> 1)::bigint t_end, a & 1 = 1 start_open, z & 1 = 1 end_open
 from (select {keys}, min(d) a, max(d) z from (select {keys}, d, d - row_number() over (partition by {keys} order by d) g from {source}) group by {keys}, g)"""


def box(name: str, source: str, keys: str, lo: int, hi: int, sign: int = -1) -> str:
    """Days whose window of days from lo to hi back (sign -1) or ahead is in the source throughout."""
    on = " and ".join(f"a.{k} = b.{k}" for k in keys.replace(" ", "").split(","))
    k = ", ".join(f"a.{x}" for x in keys.replace(" ", "").split(","))
    shift = f"a.d + {lo}" if sign < 0 else f"a.d - {lo}"
    span = f"b.d between a.d - {hi - lo} and a.d" if sign < 0 else f"b.d between a.d and a.d + {hi - lo}"
    return f"{name} as (select {k}, {shift} d from {source} a join {source} b on {on} and {span} group by {k}, a.d having count(*) = {hi - lo + 1})"


def diamond(name: str, source: str, keys: str, lo: int, hi: int) -> str:
    return f"{name} as (select distinct {keys}, d + x d from {source}, (select unnest(range({lo}, {hi} + 1)) x))"


W = "with " + STAKE + ", " + BIG + ", " + LINKED
BS = W + ", " + days("h", "big", "supp")
SQL: dict[str, str] = {}

SQL["investor_longterm"] = f"with {STAKE}, {days('h', 'stake', 'cust, supp')}, {diamond('w', 'h', 'cust, supp', 0, 30)}, {box('r', 'w', 'cust, supp', 0, 90)} {islands('r', 'cust, supp')}"
SQL["op_past_sometime"] = f"{BS}, {diamond('w', 'h', 'supp', 2, 5)} {islands('w', 'supp')}"
SQL["op_future_sometime"] = f"{BS}, {diamond('w', 'h', 'supp', -5, -2)} {islands('w', 'supp')}"
SQL["op_past_always"] = f"{BS}, {box('w', 'h', 'supp', 3, 12)} {islands('w', 'supp')}"
SQL["op_future_always"] = f"{BS}, {box('w', 'h', 'supp', 3, 12, 1)} {islands('w', 'supp')}"
SQL["op_shift"] = f"{BS}, {diamond('w', 'h', 'supp', 7, 7)} {islands('w', 'supp')}"
SQL["op_generic_t"] = f"{BS}, {diamond('w', 'h', 'supp', -4, 9)} {islands('w', 'supp')}"
SQL["op_bracket_mix"] = f"""{W}, {cells('h', 'big', 'supp')}, w as (select distinct supp, unnest(range(case when d % 2 = 0 then d + 1 else d end, d + 7)) d from h) {cell_islands('w', 'supp')}"""
SQL["chain_diamond_diamond"] = f"{BS}, {diamond('w', 'h', 'supp', -2, 2)} {islands('w', 'supp')}"
SQL["chain_box_box"] = f"{BS}, {box('u', 'h', 'supp', 0, 4)}, {box('w', 'u', 'supp', 0, 6, 1)} {islands('w', 'supp')}"
SQL["chain_box_diamond"] = f"{BS}, {diamond('u', 'h', 'supp', 0, 10)}, {box('w', 'u', 'supp', 0, 40)} {islands('w', 'supp')}"
SQL["chain_box_diamond_earliest"] = SQL["chain_box_diamond_unfused"] = SQL["chain_box_diamond"]
SQL["chain_diamond_box"] = f"{BS}, {box('u', 'h', 'supp', 0, 20)}, {diamond('w', 'u', 'supp', 0, 15)} {islands('w', 'supp')}"
SQL["coalesce_stake"] = f"with {STAKE}, {days('h', 'stake', 'cust, supp')} {islands('h', 'cust, supp')}"
SQL["coalesce_gap"] = f"""{BS}, l as (select supp, d, lag(d) over (partition by supp order by d) p from h),
 g as (select supp, d, sum(case when p is null or d - p > 11 then 1 else 0 end) over (partition by supp order by d) i from l)
 select supp, min(d)::bigint t_start, (max(d) + 1)::bigint t_end from g group by supp, i"""
SQL["merge_hotkey"] = f"{W}, k as (select supp % 2 half, s, e from big), {days('h', 'k', 'half')} {islands('h', 'half')}"
SQL["session_events"] = """with l as (select user_id, epoch_us(ts) t, lag(epoch_us(ts)) over (partition by user_id order by ts) p from events),
 g as (select user_id, t, sum(case when p is null or t - p > 21600000000 then 1 else 0 end) over (partition by user_id order by t) i from l)
 select user_id, min(t)::bigint t_start, (max(t) + 21600000000)::bigint t_end, count(*)::bigint n from g group by user_id, i"""
PAIR = "p as (select distinct a.cust c1, a.supp, b.cust c2, a.d from hb a join hb b on a.supp = b.supp and a.d = b.d and a.cust < b.cust)"
SQL["temporal_join"] = f"{W}, {days('hb', 'big', 'cust, supp')}, {PAIR} {islands('p', 'c1, supp, c2')}"
SQL["temporal_join3"] = f"{W}, {EXEMPT}, {days('hb', 'big', 'cust, supp')}, {PAIR}, q as (select p.* from p join exempt x on p.supp = x.supp and d >= x.s and d < x.e) {islands('q', 'c1, supp, c2')}"
SQL["matinee"] = """with g as (select event_id, user_id, epoch_us(ts) s, epoch_us(ts) + 7200000000 e from events where event_type = 'click'),
 w as (select x as day, 1704067200000000 + x * 86400000000 + 50400000000 s, 1704067200000000 + x * 86400000000 + 57600000000 e from (select unnest(range(0, (select max(date_diff('day', date '2024-01-01', ts::date)) + 2 from events))) x))
 select event_id, user_id, day::bigint as day, greatest(g.s, w.s)::bigint t_start, least(g.e, w.e)::bigint t_end from g join w on g.s < w.e and w.s < g.e"""
SQL["temporal_join_theta"] = f"""{BS}, o as (select s_suppkey other, s_suppkey * 17 % 2000 s from supplier),
 p as (select supp, other, d from h join o on d >= o.s and d < o.s + 25) {islands('p', 'supp, other')}"""
SQL["temporal_semi"] = f"{W}, {EXEMPT}, {days('hb', 'big', 'cust, supp')}, q as (select hb.* from hb semi join exempt x on hb.supp = x.supp and d >= x.s and d < x.e) {islands('q', 'cust, supp')}"
SQL["temporal_minus"] = f"{W}, {days('hb', 'big', 'cust, supp')}, {days('hl', 'linked', 'cust, supp')}, q as (select * from hl except select * from hb) {islands('q', 'cust, supp')}"
SETS = f"{BS}, {EXEMPT}, {days('x', 'exempt', 'supp')}"
SQL["interval_union"] = f"{SETS}, q as (select * from h union select * from x) {islands('q', 'supp')}"
SQL["interval_intersect"] = f"{SETS}, q as (select * from h intersect select * from x) {islands('q', 'supp')}"
SQL["interval_except"] = f"{SETS}, q as (select * from x except select * from h) {islands('q', 'supp')}"
SQL["own_new_owner"] = f"""{W}, {cells('h', 'big', 'cust, supp')},
 f as (select a.cust, a.supp, a.d from h a join h b on a.cust = b.cust and a.supp = b.supp and b.d between a.d and a.d + 2 group by a.cust, a.supp, a.d having count(*) = 3),
 p as (select distinct cust, supp, unnest(range(case when d % 2 = 0 then d + 1 else d end, d + 3)) d from h),
 q as (select * from f except select * from p) {cell_islands('q', 'cust, supp')}"""
CONV = "a as (select distinct conv_id, turn from conversations where role = 'assistant'), u as (select distinct conv_id, turn from conversations where role = 'user')"
SQL["conv_since"] = f"""with {CONV}, t as (select distinct conv_id, turn + x d, turn s from u, (select unnest(range(0, 4)) x)),
 q as (select distinct conv_id, d from t where not exists (select 1 from (select unnest(range(s + 1, d)) r) where r not in (select turn from a where a.conv_id = t.conv_id))) {islands('q', 'conv_id', '', 'max(d)')}"""
SQL["conv_until"] = f"""with {CONV}, t as (select distinct conv_id, turn - x d, turn s from u, (select unnest(range(1, 4)) x)),
 q as (select distinct conv_id, d from t where not exists (select 1 from (select unnest(range(d + 1, s)) r) where r not in (select turn from a where a.conv_id = t.conv_id))) {islands('q', 'conv_id', '', 'max(d)')}"""
CALM = """with ev as (select user_id, event_type, value, (epoch_us(ts) - 1704067200000000) // 3600000000 h from events),
 hr as (select user_id, h, max(value) v from ev group by user_id, h),
 nx as (select user_id, h s, coalesce(lead(h) over (partition by user_id order by h), h + 24) e, v from hr),
 c as (select distinct user_id, unnest(range(2 * s, 2 * e)) d from nx where v < 150),
 ci as (select user_id, min(d) a, max(d) z from (select user_id, d, d - row_number() over (partition by user_id order by d) g from c) group by user_id, g),
 b as (select distinct user_id, h from ev where event_type = 'signup')"""
SQL["ev_since"] = f"""{CALM}, t as (select user_id, h, 2 * h + x d from b, (select unnest(range(0, 25)) x)),
 q as (select distinct user_id, d from t where d <= 2 * h or exists (select 1 from ci where ci.user_id = t.user_id and a <= 2 * h + 1 and z >= (case when d % 2 = 0 then d - 1 else d end)))
 {cell_islands('q', 'user_id')}"""
SQL["ev_until"] = f"""{CALM}, t as (select user_id, h, 2 * h - x d from b, (select unnest(range(0, 25)) x)),
 q as (select distinct user_id, d from t where d >= 2 * h or exists (select 1 from ci where ci.user_id = t.user_id and a <= (case when d % 2 = 0 then d + 1 else d end) and z >= 2 * h - 1))
 {cell_islands('q', 'user_id')}"""
for f, sql in (("sum", "round(sum(price::decimal(28,6))::double, 2)"), ("count", "count(*)::double"), ("max", "max(price)"), ("min", "min(price)")):
    SQL[f"agg_instant_{f}"] = f"""{W}, k as (select cust, supp, price, s, e from stake), {days('h', 'k', 'cust, supp, price')},
 v as (select supp, d, {sql} as value from h group by supp, d) {islands('v', 'supp, value')}"""
SQL["agg_monotonic"] = f"""{W}, k as (select cust, supp, price, s, e from stake), {days('h', 'k', 'cust, supp, price')},
 m as (select supp, cust, d, max(price) p from h group by supp, cust, d), v as (select supp, d, round(sum(p::decimal(28,6))::double, 2) as value from m group by supp, d) {islands('v', 'supp, value')}"""
SQL["agg_history"] = f"""with {STAKE}, {days('h', 'stake', 'cust, supp, price')}, i as ({islands('h', 'cust, supp, price')})
 select supp, count(*)::bigint facts, max(price) dearest, count(distinct cust)::bigint buyers from i group by supp"""
SQL["lift_month"] = f"""{BS}, m as (select distinct supp, date_trunc('month', date '1995-01-01' + d::int) u from h),
 z as (select supp, {DAY.format('u')} s, {DAY.format("(u + interval 1 month)")} e from m), {days('q', 'z', 'supp')} {islands('q', 'supp')}"""
SQL["rollup_units"] = "select year(o_orderdate)::int y, month(o_orderdate)::int m, sum(o_totalprice::decimal(18,2))::double total, count(*)::bigint n from orders group by rollup (year(o_orderdate), month(o_orderdate))"
SQL["covered_time"] = f"{BS} select supp, count(*)::bigint covered from h group by supp"


def own(edge: str, guard: str = "true") -> str:
    return f"""with recursive {STAKE}, {BIG}, {LINKED}, {SEED}, {EXEMPT}, {days('hb', 'big', 'cust, supp')}, {days('hl', 'linked', 'cust, supp')}, {days('hs', 'stake', 'cust, supp')},
 {edge}, x as (select distinct e.supp y, l.supp z, l.d from e join hl l on e.cust = l.cust and e.d = l.d where {guard}),
 w(supp, d) as (select supp, d::bigint d from (select supp, unnest(range(s, e)) d from seed) union select z, x.d from w join x on w.supp = x.y and w.d = x.d)
 {islands('w', 'supp')}"""


DIAMOND_EDGE = diamond("e", "hb", "cust, supp", 0, 30)
SQL["own_temporal"] = SQL["own_temporal_naive"] = own(DIAMOND_EDGE, "e.supp <> l.supp")
SQL["own_negation"] = own(DIAMOND_EDGE, "e.supp <> l.supp and not exists (select 1 from exempt q where q.supp = l.supp and l.d >= q.s and l.d < q.e)")
SQL["own_diamond"] = own(DIAMOND_EDGE)
for p in ("minimal", "earliest", "always"):
    SQL[f"own_box_{p}"] = own(box("e", "hs", "cust, supp", 0, 20))
for p in ("minimal", "earliest", "always", "auto"):
    SQL[f"own_wide_{p}"] = own(f"{diamond('u', 'hs', 'cust, supp', 0, 10)}, {box('e', 'u', 'cust, supp', 0, 40)}")
SQL["own_aggregation"] = f"with {STAKE}, {days('h', 'stake', 'cust, supp, price')}, v as (select supp, d from h group by supp, d having sum(price) > 400000) {islands('v', 'supp')}"

STEADY = f"""pl as (select o_custkey cust, {DAY.format('o_orderdate')} d0 from orders),
 ac as (select distinct cust, unnest(range(2 * d0, 2 * d0 + 61)) d from pl),
 ai as (select cust, min(d) a, max(d) z from (select cust, d, d - row_number() over (partition by cust order by d) g from ac) group by cust, g),
 st as (select cust, unnest(range(a + 120, z + 1)) d from ai)"""
SQL["hier_steady"] = f"with {STEADY} {cell_islands('st', 'cust')}"
SQL["hier_nonrec"] = f"""with {STEADY}, q as (select distinct n_regionkey::bigint region, d from st join customer on cust = c_custkey join nation on c_nationkey = n_nationkey) {cell_islands('q', 'region')}"""
SQL["hier_rec"] = """with recursive e as (select 'c' || c_custkey x, 'n' || c_nationkey y from customer union select 'n' || n_nationkey, 'r' || n_regionkey from nation),
 m(x, y) as (select x, y from e union select m.x, e.y from m join e on m.y = e.x)
 select x, y, null::bigint t_start, null::bigint t_end, true start_open, true end_open from m"""
SQL["hier_affected"] = f"""with recursive {STAKE}, {BIG}, {days('hb', 'big', 'cust, supp')},
 sm as (select distinct a.cust c, b.cust o, a.d from hb a join hb b on a.supp = b.supp and a.d = b.d and a.cust <> b.cust),
 w(cust, d) as (select o_custkey, {DAY.format('o_orderdate')} from orders where o_orderpriority = '1-URGENT' and o_totalprice > 400000
 union select sm.c, sm.d from w join sm on sm.o = w.cust and sm.d between w.d + 1 and w.d + 7) {islands('w', 'cust')}"""

READ = "rd as (select user_id, value, epoch_us(ts) s, lead(epoch_us(ts)) over (partition by user_id order by ts) e from events)"


def held(name: str, condition: str) -> str:
    """Islands of readings under a condition; null: for ever."""
    return f"""{name}0 as (select user_id, s, coalesce(e, 9000000000000000000) e from rd where {condition}),
 {name}1 as (select *, case when lag(e) over (partition by user_id order by s) = s then 0 else 1 end f from {name}0),
 {name}2 as (select *, sum(f) over (partition by user_id order by s) i from {name}1),
 {name} as (select user_id, min(s) s, max(e) e from {name}2 group by user_id, i)"""


SQL["meteo_heat"] = f"with {READ}, {held('a', 'value > 50')} select user_id, (s + 21600000000)::bigint t_start, (case when e < 9000000000000000000 then e end)::bigint t_end from a where s + 21600000000 < e"
SQL["meteo_wind"] = f"""with {READ}, {held('st', 'value > 110')}, {held('qu', 'value < 5')},
 wi as (select user_id, s, case when e < 9000000000000000000 then e + 86400000000 else e end e from st),
 w1 as (select *, max(e) over (partition by user_id order by s rows between unbounded preceding and 1 preceding) m from wi),
 w2 as (select *, sum(case when m is null or s > m then 1 else 0 end) over (partition by user_id order by s) i from w1),
 w as (select user_id, min(s) s, max(e) e from w2 group by user_id, i),
 c as (select user_id, s x from w union select user_id, e from w union select q.user_id, q.s from qu q union select user_id, e from qu),
 g as (select user_id, x, lead(x) over (partition by user_id order by x) y from c),
 k as (select g.* from g where y is not null and exists (select 1 from w where w.user_id = g.user_id and w.s <= x and y <= w.e)
 and not exists (select 1 from qu where qu.user_id = g.user_id and qu.s <= x and y <= qu.e)),
 k1 as (select *, case when lag(y) over (partition by user_id order by x) = x then 0 else 1 end f from k), k2 as (select *, sum(f) over (partition by user_id order by x) i from k1)
 select user_id, min(x)::bigint t_start, (case when max(y) < 9000000000000000000 then max(y) end)::bigint t_end from k2 group by user_id, i"""

SQL["gen_box"] = f"with {STAKE}, {days('h', 'stake', 'cust, supp')}, i as ({islands('h', 'cust, supp')}) select cust, supp, t_start + 30 t_start, t_end from i where t_start + 30 < t_end"
SQL["gen_diamond"] = f"with {STAKE}, {days('h', 'stake', 'cust, supp')}, {diamond('w', 'h', 'cust, supp', 0, 30)} {islands('w', 'cust, supp')}"
MOVED = f"{W}, mv as (select cust, supp, s + 5 s, e + 5 e from linked), {days('ha', 'big', 'cust, supp')}, {days('hc', 'mv', 'cust, supp')}"
SQL["gen_union"] = f"{MOVED}, q as (select * from ha union select * from hc) {islands('q', 'cust, supp')}"
SQL["gen_intersection"] = f"{MOVED}, q as (select * from ha intersect select * from hc) {islands('q', 'cust, supp')}"

SHIPPED = f"""with v as (select {DAY.format('l_shipdate')} d, sum(l_extendedprice * (1 - l_discount)) v from lineitem group by 1),
 h as (select d from v where v > (select quantile_cont(v, 0.9) from v)), r as (select distinct 30 * x + y d from (select unnest(range(0, 200)) x), (select unnest(range(0, 4)) y))"""
SQL["report_cause"] = f"{SHIPPED} select d::bigint d, 1 kind, d::bigint t_start, d::bigint t_end, false start_open, false end_open from h where d in (select d from r)"
SQL["pattern_minus_rules"] = f"{SHIPPED} select d::bigint d, d::bigint t_start, d::bigint t_end, false start_open, false end_open from h where d not in (select d from r)"
SQL["pattern_rules"] = f"""with x as (select unnest(range(0, 200)) x), r as (select distinct 60 * x + y c from x, (select unnest(range(0, 3)) y)), a as (select distinct 14 * x + y c from x, (select unnest(range(0, 5)) y)),
 l as (select distinct 60 * x + y c from x, (select unnest(range(2, 9)) y)),
 q as (select 1 kind, c d from r where c in (select c from a) union select 1, c from l), z as (select kind, d from q where d between 0 and 800) {cell_islands('z', 'kind')}"""
SQL["pattern_answer"] = "select 1 kind, 30::bigint as every, -2::bigint t_start, 0::bigint t_end, false start_open, false end_open"
SQL["weekday_orders"] = f"select ({DAY.format('o_orderdate')} % 7)::bigint dow, o_orderpriority, count(*)::bigint n from orders group by 1, 2"
SQL["weekday_rules"] = SQL["weekday_orders"]
SQL["pattern_unroll"] = "select n_nationkey::bigint k, (n_nationkey + 31 * x)::bigint t_start, (n_nationkey + 31 * x + 2)::bigint t_end from nation, (select unnest(range(0, 10)) x) where n_nationkey + 31 * x < 200"
SQL["constant_reach"] = """with f as (select user_id, min((epoch_us(ts) - 1704067200000000) // 3600000000) h from events where event_type = 'error' group by user_id)
 select user_id, h::bigint t_start, h::bigint t_end, false start_open, false end_open from f
 union all select user_id, (h + 1)::bigint, null::bigint, false, true from f"""

DAILY = f"""s as (select l_returnflag, l_linestatus, {DAY.format('l_shipdate')} t, sum(l_extendedprice::decimal(12,2) * (1 - l_discount::decimal(4,2)))::double v from lineitem group by 1, 2, 3)"""
K = "l_returnflag, l_linestatus"
SELF = "a.l_returnflag = b.l_returnflag and a.l_linestatus = b.l_linestatus"


def frame(before: int, after: int, f: str, having: str, shift: str = "", digits: int = 2) -> str:
    return f"select a.l_returnflag, a.l_linestatus, a.t{shift} t, round({f}, {digits}) v from s a join s b on {SELF} and b.t between a.t - {before} and a.t + {after} group by 1, 2, a.t {having}"


TREND = f"tr as (select a.l_returnflag, a.l_linestatus, a.t, avg(b.v) v from s a join s b on {SELF} and b.t between a.t - 6 and a.t group by 1, 2, 3 having count(*) = 7), t7 as (select {K}, t - 3 t, v from tr), de as (select s.l_returnflag, s.l_linestatus, s.t, s.v - t7.v v from s join t7 using (l_returnflag, l_linestatus, t)), se as (select {K}, t % 7 p, avg(v) m from de group by all)"
SQL["ts_shift"] = f"with {DAILY} select {K}, t + 1 t, round(v, 4) v from s"
SQL["ts_rolling"] = f"with {DAILY} {frame(2, 0, 'sum(b.v)', 'having count(*) = 3', digits=4)}"
SQL["ts_rolling_partial"] = f"with {DAILY} {frame(2, 0, 'max(b.v)', '', digits=4)}"
SQL["ts_sma"] = f"with {DAILY} {frame(6, 0, 'avg(b.v)', 'having count(*) = 7', digits=6)}"
SQL["ts_cma"] = f"with {DAILY} {frame(6, 0, 'avg(b.v)', 'having count(*) = 7', ' - 3', 6)}"
SQL["ts_cma_even"] = f"""with {DAILY}, x as (select a.l_returnflag, a.l_linestatus, a.t, sum(case when abs(b.t - a.t) = 6 then b.v / 2 else b.v end) / 12 v from s a join s b on {SELF} and b.t between a.t - 6 and a.t + 6 group by 1, 2, 3 having count(*) = 13)
 select {K}, t, round(v, 7) v from x"""
SQL["ts_ema"] = f"""with recursive {DAILY}, r as (select *, row_number() over (partition by {K} order by t) i from s),
 e(l_returnflag, l_linestatus, i, t, y) as (select {K}, 10, max(t), avg(v) from r where i <= 10 group by {K} having count(*) = 10
 union all select r.l_returnflag, r.l_linestatus, r.i, r.t, 2.0::double / 11 * r.v + (1 - 2.0::double / 11) * e.y from e join r on r.l_returnflag = e.l_returnflag and r.l_linestatus = e.l_linestatus and r.i = e.i + 1)
 select {K}, t, round(y, 2) v from e"""
SQL["ts_ema_blocks"] = SQL["ts_ema"]
SQL["ts_ema_rules"] = SQL["ts_ema"]
SQL["ts_stock_to_flow"] = f"with {DAILY} select a.l_returnflag, a.l_linestatus, a.t, round(a.v - b.v, 4) v from s a join s b on {SELF} and b.t = a.t - 1"
SQL["ts_flow_to_stock"] = f"with {DAILY} select {K}, t, round(sum(v) over (partition by {K} order by t), 4) v from s"
SQL["ts_downsample"] = f"with {DAILY} select {K}, (t // 30)::bigint t, round(avg(v), 2) v from s group by all"
SQL["ts_trend"] = f"with {DAILY}, {TREND} select {K}, t, round(v, 6) v from t7"
SQL["ts_detrend"] = f"with {DAILY}, {TREND} select {K}, t, round(v, 6) v from de"
SQL["ts_seasonal"] = f"with {DAILY}, {TREND} select de.l_returnflag, de.l_linestatus, t, round(m, 2) v from de join se on de.l_returnflag = se.l_returnflag and de.l_linestatus = se.l_linestatus and t % 7 = p"
SQL["ts_residual"] = f"with {DAILY}, {TREND} select de.l_returnflag, de.l_linestatus, t, round(v - m, 2) v from de join se on de.l_returnflag = se.l_returnflag and de.l_linestatus = se.l_linestatus and t % 7 = p"
ORD = f"o as (select o_orderpriority priority, {DAY.format('o_orderdate')} t, count(*)::double v from orders group by 1, 2)"
WEEK = f"{ORD}, w as (select priority, (t // 7) * 7 t, sum(v) v from o group by 1, 2), n as (select *, lead(t) over (partition by priority order by t) nt, lead(v) over (partition by priority order by t) nv from w), z as (select *, unnest(range(t, coalesce(nt, t + 1))) z from n)"
SQL["ts_upsample"] = f"with {WEEK} select priority, z::bigint t, round(case when z = t then v else v + (nv - v) * (z - t) / (nt - t) end, 4) v from z"
SQL["ts_upsample_rules"] = f"with {WEEK.replace('coalesce(nt, t + 1)', 'case when nt = t + 7 then nt else t + 1 end')} select priority, z::bigint t, round(case when z = t then v else v + (nv - v) * (z - t) / (nt - t) end, 4) v from z"
SQL["ts_upsample_hold"] = f"with {WEEK} select priority, z::bigint t, round(v, 4) v from z"
SQL["ts_rolling_rules"] = f"with {ORD} select a.priority, a.t::bigint t, sum(b.v) v from o a join o b on a.priority = b.priority and b.t between a.t - 2 and a.t group by 1, 2 having count(*) = 3"
SQL["ts_frequency"] = f"with {ORD}, d as (select priority, t - lag(t) over (partition by priority order by t) d from o) select priority, min(d)::bigint as least, max(d)::bigint as most, coalesce(min(d) = max(d), true) regular from d group by priority"
SQL["ts_add"] = f"with {ORD} select a.priority, a.t::bigint t, round(a.v + b.v, 2) v from o a join o b on a.priority = b.priority and b.t = a.t - 1"
SQL["ts_embedding_sma"] = """with e as (select vec_id, unnest(range(0, len(embedding))) t, unnest(embedding)::double v from embeddings)
 select a.vec_id, a.t::bigint t, round(avg(b.v), 4) v from e a join e b on a.vec_id = b.vec_id and b.t between a.t - 7 and a.t group by 1, 2 having count(*) = 8"""
SQL["ts_event_seasonal"] = """with s as (select event_type, date_diff('day', date '2024-01-01', ts::date) t, sum(value::decimal(18,4))::double v from events group by 1, 2),
 tr as (select a.event_type, a.t, avg(b.v) m from s a join s b on a.event_type = b.event_type and b.t between a.t - 3 and a.t + 3 group by 1, 2 having count(*) = 7),
 de as (select s.event_type, s.t, v - m v from s join tr on s.event_type = tr.event_type and s.t = tr.t), se as (select event_type, t % 7 p, avg(v) m from de group by all)
 select de.event_type, de.t::bigint t, round(m, 2) v from de join se on de.event_type = se.event_type and t % 7 = p"""
SQL["wrap_roundtrip"] = f"select o_custkey cust, o_orderkey ord, {DAY.format('o_orderdate')} t_start, {DAY.format('o_orderdate')} t_end from orders where o_orderkey in (select doc_id from labels where quality = 1)"
SQL["relations13"] = f"""{W}, j as (select a.s a, a.e b, x.s c, x.e d from big a join big x on a.supp = x.supp and a.cust < x.cust)
 select case when b < c then 'before' when b = c then 'meets' when d < a then 'after' when d = a then 'met_by' when a = c and b = d then 'equals'
 when a = c and b < d then 'starts' when a = c then 'started_by' when b = d and a > c then 'finishes' when b = d then 'finished_by'
 when a < c and b > d then 'contains' when a > c and b < d then 'during' when a < c then 'overlaps' else 'overlapped_by' end relation, count(*)::bigint n from j group by 1"""
SQL["hold_readings"] = f"with {READ} select user_id, value, s::bigint t_start, e::bigint t_end from rd"
SQL["sweep_counts"] = f"""{W}, {days('hb', 'big', 'cust, supp')}, i as ({islands('hb', 'cust, supp')}), x as (select distinct supp, t from (select supp, t_start t from i union all select supp, t_end from i)),
 c as (select x.supp, x.t, (select count(*) from i where i.supp = x.supp and t_start <= x.t and x.t < t_end) n, (select count(*) from i where i.supp = x.supp and t_start <= x.t - 1 and x.t - 1 < t_end) p from x)
 select supp, t::bigint t, n::bigint n from c where (select count(*) from i where i.supp = c.supp and t_start = c.t) <> (select count(*) from i where i.supp = c.supp and t_end = c.t)"""
SQL["top_intervals"] = f"{BS}, i as ({islands('h', 'supp')}), r as (select *, row_number() over (partition by supp order by t_end - t_start desc, t_start) as rank from i) select supp, t_start, t_end, rank::int as rank from r where rank <= 3"


def states(keys: str, source: str) -> str:
    """Islands of every prefix of a key's facts by price that the latest fact changed: the island that it is in."""
    k = keys.replace(" ", "").split(",")
    on = " and ".join(f"a.{x} = f.{x}" for x in k)
    part = ", ".join(k)
    return f"""f0 as (select {part}, 2 * s lo, 2 * e - 1 hi, min(price) price from {source} group by all), f as (select *, row_number() over (partition by {part} order by price, lo, hi) i from f0),
 p as (select {', '.join('f.' + x for x in k)}, f.i, f.lo flo, f.hi fhi, a.lo, a.hi, max(a.hi) over (partition by {', '.join('f.' + x for x in k)}, f.i order by a.lo, a.hi rows between unbounded preceding and 1 preceding) m from f join f a on {on} and a.i <= f.i),
 g as (select *, sum(case when m is null or lo > m + 1 then 1 else 0 end) over (partition by {part}, i order by lo, hi rows between unbounded preceding and current row) n from p),
 w as (select {part}, i, flo, fhi, n, min(lo) a, max(hi) b from g group by all), now as (select * from w where a <= flo and fhi <= b),
 c as (select {', '.join('now.' + x for x in k)}, now.i, a, b, flo, fhi from now),
 old as (select {', '.join('c.' + x for x in k)}, c.i, c.a, c.b, exists (select 1 from now o where {' and '.join(f'o.{x} = c.{x}' for x in k)} and o.i < c.i and o.a <= c.flo and c.fhi <= o.b) covered from c)
 select {part}, (a >> 1)::bigint t_start, ((b + 1) >> 1)::bigint t_end from old where not covered"""


SQL["merge_streaming"] = f"{W}, k as (select * from stake where price > 94700), {states('supp', 'k')}"
SQL["wrap_rules"] = f"""with {STAKE}, {days('h', 'stake', 'cust, supp')}, i as ({islands('h', 'cust, supp')}),
 x as (select sha256(concat_ws('|', 'deal', 'D', cust, supp, t_start, t_end)) deal, cust, t_start s, t_end + 5 e from i where t_end - t_start > 45), {days('q', 'x', 'deal, cust')} {islands('q', 'deal, cust')}"""
#: The operators over every stake, by customer and supplier.
CS = f"with {STAKE}, {days('h', 'stake', 'cust, supp')}"
SQL["op_past_sometime_all"] = f"{CS}, {diamond('w', 'h', 'cust, supp', 2, 5)} {islands('w', 'cust, supp')}"
SQL["op_future_sometime_all"] = f"{CS}, {diamond('w', 'h', 'cust, supp', -5, -2)} {islands('w', 'cust, supp')}"
SQL["op_past_always_all"] = f"{CS}, {box('w', 'h', 'cust, supp', 3, 12)} {islands('w', 'cust, supp')}"
SQL["op_future_always_all"] = f"{CS}, {box('w', 'h', 'cust, supp', 3, 12, 1)} {islands('w', 'cust, supp')}"
SQL["op_shift_all"] = f"{CS}, {diamond('w', 'h', 'cust, supp', 7, 7)} {islands('w', 'cust, supp')}"
SQL["op_generic_t_all"] = f"{CS}, {diamond('w', 'h', 'cust, supp', -4, 9)} {islands('w', 'cust, supp')}"
SQL["op_bracket_mix_all"] = f"""with {STAKE}, {cells('h', 'stake', 'cust, supp')}, w as (select distinct cust, supp, unnest(range(case when d % 2 = 0 then d + 1 else d end, d + 7)) d from h) {cell_islands('w', 'cust, supp')}"""
SQL["chain_diamond_diamond_all"] = f"{CS}, {diamond('w', 'h', 'cust, supp', -2, 2)} {islands('w', 'cust, supp')}"
SQL["chain_box_box_all"] = f"{CS}, {box('u', 'h', 'cust, supp', 0, 4)}, {box('w', 'u', 'cust, supp', 0, 6, 1)} {islands('w', 'cust, supp')}"
SQL["chain_box_diamond_all"] = f"{CS}, {diamond('u', 'h', 'cust, supp', 0, 10)}, {box('w', 'u', 'cust, supp', 0, 40)} {islands('w', 'cust, supp')}"
SQL["chain_box_diamond_earliest_all"] = SQL["chain_box_diamond_unfused_all"] = SQL["chain_box_diamond_all"]
SQL["chain_diamond_box_all"] = f"{CS}, {box('u', 'h', 'cust, supp', 0, 20)}, {diamond('w', 'u', 'cust, supp', 0, 15)} {islands('w', 'cust, supp')}"
SQL["coalesce_gap_all"] = f"""{CS}, l as (select cust, supp, d, lag(d) over (partition by cust, supp order by d) p from h),
 g as (select cust, supp, d, sum(case when p is null or d - p > 11 then 1 else 0 end) over (partition by cust, supp order by d) i from l)
 select cust, supp, min(d)::bigint t_start, (max(d) + 1)::bigint t_end from g group by cust, supp, i"""
SQL["merge_hotkey_all"] = f"with {STAKE}, k as (select supp % 2 half, s, e from stake), {days('h', 'k', 'half')} {islands('h', 'half')}"
SQL["lift_month_all"] = f"""{CS}, m as (select distinct cust, supp, date_trunc('month', date '1995-01-01' + d::int) u from h),
 z as (select cust, supp, {DAY.format('u')} s, {DAY.format("(u + interval 1 month)")} e from m), {days('q', 'z', 'cust, supp')} {islands('q', 'cust, supp')}"""
SQL["covered_time_all"] = f"{CS} select cust, supp, count(*)::bigint covered from h group by cust, supp"
SQL["merge_streaming_all"] = f"with {STAKE}, {states('cust, supp', 'stake')}"
