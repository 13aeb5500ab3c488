"""Evaluation of programs, stratum by stratum and round by round."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import DAYS, HI, LO, NEG, POS, Range, TemporalRelation, Timeline
from ..operators.merge import coalesce, novel
from ..staging import forget, staged, together
from . import analysis, planner
from .language import Aggregate, Compare, Fresh, Literal, Program, Rule, RuleError, Var, parse, validate
from .patterns import NeedsWindow, PatternRelation, accelerate_constant, admit, common_period, only_pattern, with_repeats
from .recurrence import Carried, Stepping, carry_on, punctual, recognise_recurrence
from .rewrite import canonicalise, fuse_chains
from .slices import Step, slicing, solve_slices


@dataclass(frozen=True)
class Options:
    """placement: minimal, earliest, always, or auto (the cheapest by estimates of a sample); strategy: naive or seminaive;
    fuse: compose operator chains; canonical: split rules into single operators and joins first;
    hints: extra merges ('union', 'diamond', 'input', 'output'); static: evaluate and join what does not depend on a recursion once,
    not in every round; merge_every: rounds after which the tables of a recursive predicate become one; ahead: steps that a round takes at
    once where the last one added less than an eighth of what is known (1: always one); slice_rows: most facts of a slice of time that
    one task may solve by itself, where the recursion does not move facts (0: rounds are always distributed)."""

    placement: str = "minimal"
    strategy: str = "seminaive"
    fuse: bool = True
    max_rounds: int = 200
    horizon: tuple[int, int] | None = None
    hints: frozenset = frozenset()
    canonical: bool = False
    static: bool = True
    merge_every: int = 8
    ahead: int = 4
    slice_rows: int = 1_000_000


@dataclass
class Report:
    """Rows that each round added, by recursive group; placements chosen; rows through nodes where they were counted."""

    rounds: dict[str, list[int]] = field(default_factory=dict)
    kind: str = "finite"
    clipped: bool = False
    chosen: dict[str, str] = field(default_factory=dict)


def _union(parts: list[TemporalRelation]) -> TemporalRelation:
    if len(parts) == 1:
        return parts[0]
    keys = parts[0].keys
    return parts[0].with_df(reduce(lambda a, b: a.unionByName(b), [p.df.toDF(*keys, LO, HI) if p.keys != keys else p.df.select(*keys, LO, HI) for p in parts]))


def _numbered(r: TemporalRelation) -> TemporalRelation:
    """Keys by their place, as derived predicates have them."""
    names = [f"c{i}" for i in range(len(r.keys))]
    steps = lambda p: tuple((f"c{r.keys.index(k)}", v) for k, v in p.steps)
    plain = lambda x: x.with_df(x.df.select(*(F.col(k).alias(n) for k, n in zip(x.keys, names)), LO, HI), names, x.coalesced)
    out = plain(r)
    return out if r.repeats is None else with_repeats(out, replace(r.repeats, base=plain(r.repeats.base), steps=steps(r.repeats)))


def _within(r: TemporalRelation, a: int, b: int, by: int = 0) -> TemporalRelation:
    """The parts of facts in cells [a, b], moved."""
    cut = r.df.select(*r.keys, (F.greatest(LO, F.lit(a)) + by).alias(LO), (F.least(HI, F.lit(b)) + by).alias(HI)).where(F.col(LO) <= F.col(HI))
    return r.with_df(cut, coalesced=r.coalesced)


class Engine:
    """Evaluates a program over named base relations.

    ``env`` holds what is known of every predicate; a relation in it may have a pattern of facts that repeat for
    ever besides its rows (also in ``patterns``).
    """

    def __init__(self, program: Program | str, facts: dict[str, TemporalRelation], options: Options = Options()):
        self.program = parse(program) if isinstance(program, str) else program
        if options.fuse:
            self.program = fuse_chains(self.program, keep=True)
        if options.canonical:
            self.program = canonicalise(self.program)
        self.facts, self.o, self.report = dict(facts), options, Report()
        validate(self.program, {p: len(r.keys) for p, r in facts.items()})
        self.report.kind = analysis.model_kind(self.program)
        self.timeline: Timeline = next(iter(facts.values())).timeline if facts else DAYS
        self.patterns: dict[str, PatternRelation] = {}
        self.env: dict[str, TemporalRelation] = {}
        self.observe = None
        self._stats: dict[str, planner.Stats] = {}

    def run(self) -> "Engine":
        heads = self.program.heads()
        self.env = {p: (with_repeats(coalesce(r), r.repeats) if self.o.placement == "always" or "input" in self.o.hints else r) for p, r in self.facts.items()}
        self.patterns = {p: r.repeats for p, r in self.facts.items() if r.repeats is not None}
        recursive = {p: tuple(g) for g in analysis.recursive_groups(self.program) for p in g}
        done = set()
        for group in analysis.components(self.program):
            mine = [p for p in group if p in heads and p not in done]
            done |= set(mine)
            if not mine:
                continue
            if group[0] in recursive:
                self._fixpoint(mine)
            else:
                self._know(mine[0], self._all_rules(mine[0]))
        return self

    # Single rules.
    def _plan(self, rule: Rule, deltas: dict[int, str] | None = None, parts: tuple = (), env: dict | None = None) -> planner.Node:
        known = self.env if env is None else env
        late = frozenset(i for i, x in enumerate(rule.literals) if any(a.predicate in known and known[a.predicate].repeats is not None for a in x.atoms()))
        node = planner.compile_rule(rule, deltas, parts, late)
        if self.o.placement != "auto":
            return planner.place_merges(planner.moves(node, self.timeline, self.o.fuse), self.o.placement, self.o.hints - {"output"}, self.timeline)
        for x in node.walk():
            if x.kind == "Scan" and x.detail in self.facts and x.detail not in self._stats:
                self._stats[x.detail] = planner.sample_stats(self.facts[x.detail])
        name, plan = planner.choose(node, self._stats, None, self.timeline, self.o.fuse)
        self.report.chosen[rule.text.strip()] = name
        return plan

    def relation(self, rule: Rule, env: dict[str, TemporalRelation] | None = None, deltas: dict[int, str] | None = None, parts: tuple = ()) -> TemporalRelation:
        """The facts that one rule derives; where facts that repeat for ever meet an operator that needs it, by a window."""
        env = self.env if env is None else env
        try:
            return planner.to_relation(self._plan(rule, deltas, parts, env), env, self.observe)
        except NeedsWindow:
            return self._by_window(rule, env, deltas, parts)

    def _by_window(self, rule: Rule, env: dict, deltas=None, parts=()) -> TemporalRelation:
        """A rule over facts that repeat: beyond the last end of what does not repeat, and the operators' reach, the answer
        repeats with the common period of what is read; so much is evaluated on written out occurrences."""
        read = {(deltas or {}).get(i, a.predicate) for i, x in enumerate(rule.literals) for a in x.atoms() if a.predicate != "top"} | {p.name for p in parts}
        known = {p: env[p] for p in read if p in env}
        moving = {p: r.repeats for p, r in known.items() if r.repeats is not None}
        if any(p.steps for p in moving.values()):
            raise RuleError(f"values of {sorted(p for p in moving if moving[p].steps)} go on for ever: join them with facts that end")
        scale = self.timeline.scale
        reach = 0
        for x in rule.literals:
            far = _reach(x)
            if far is None:
                raise RuleError(f"{rule.text.strip()}: an unbounded operator over facts that repeat for ever")
            reach = max(reach, scale * far)
        period = common_period([p.period for p in moving.values()])
        last, wide = 0, 0
        for r in known.values():
            e = r.df.agg(F.max(F.when(F.col(HI) < POS, F.col(HI))).alias("b"), F.max(F.when(F.col(LO) > NEG, F.col(LO))).alias("a")).first()
            last = max(last, *(e[k] + 1 for k in ("a", "b") if e[k] is not None), last)
        for p in moving.values():
            e = p.base.df.agg(F.max(HI).alias("b"), F.max(F.col(HI) - F.col(LO)).alias("w")).first()
            if e["b"] is not None:
                last, wide = max(last, e["b"] + 1 + p.n0 * p.period), max(wide, e["w"])
        begin = last + reach + wide + 1
        end = begin + 2 * period + reach + wide + 1
        whole = {**env, **{p: known[p].with_df(known[p].df.select(*known[p].keys, LO, HI).unionByName(q.unroll(NEG // 4, end).df.select(*known[p].keys, LO, HI))) for p, q in moving.items()}}
        got = coalesce(planner.to_relation(self._plan(rule, deltas, parts, whole), whole, self.observe))
        got = got.with_df(staged(got.df, "window"), coalesced=True)
        covers = (F.col(LO) <= begin) & (F.col(HI) >= begin + period - 1)
        endless = got.df.where(covers).select(*got.keys, LO, F.lit(POS).alias(HI))
        rest = got.with_df(got.df.where(~covers))
        rows = got.with_df(_within(rest, NEG, begin - 1).df.unionByName(endless))
        block = _within(rest, begin, begin + period - 1)
        return rows if block.df.isEmpty() else with_repeats(rows, PatternRelation(block, period))

    def _all_rules(self, p: str, rules: list[Rule] | None = None, env: dict | None = None) -> TemporalRelation | None:
        """What rules (all of p's) and base facts say of p."""
        parts = [self.relation(r, env) for r in (self.program.for_head(p) if rules is None else rules)]
        if p in self.facts:
            parts.append(_numbered(self.facts[p]))
        if not parts:
            return None
        out = _union(parts)
        patterns = [x.repeats for x in parts if x.repeats is not None]
        if patterns:
            out = with_repeats(out, planner.merged_patterns([replace(q, base=q.base.with_df(q.base.df.toDF(*out.keys, LO, HI), out.keys)) for q in patterns]))
        return with_repeats(coalesce(out), out.repeats) if self.o.placement == "always" or "union" in self.o.hints and len(parts) > 1 else out

    def _know(self, p: str, r: TemporalRelation) -> None:
        self.env[p] = r
        if r.repeats is not None:
            self.patterns[p] = r.repeats

    # Recursion.
    def _self_loop(self, p: str, rules: list[Rule]) -> tuple[list[Rule], Range] | None:
        """p(X) :- past[t1,t2] p(X) beside rules that do not read p."""
        loops = [r for r in rules if any(a.predicate == p for x in r.literals for a in x.atoms())]
        if len(loops) != 1 or len(loops[0].literals) != 1 or loops[0].conditions:
            return None
        x = loops[0].literals[0]
        if x.binary or x.negated or x.atom.span or len(x.ops) != 1 or x.ops[0][0] != "past" or x.atom.terms != loops[0].head.terms or loops[0].head.span:
            return None
        return [r for r in rules if r is not loops[0]], x.ops[0][1]

    def _fixpoint(self, group: list[str]) -> None:
        rules = [r for p in group for r in self.program.for_head(p)]
        label = "+".join(group)
        if len(group) == 1 and (loop := self._self_loop(group[0], rules)):
            # Closed forms: no rounds at all.
            p = group[0]
            base = self._all_rules(p, loop[0])
            if loop[1].lo == loop[1].hi and not loop[1].lo_open:
                self._repeat(p, base, PatternRelation(coalesce(base), loop[1].lo * base.timeline.scale))
            else:
                self.env[p] = accelerate_constant(base, loop[1])
            self.report.rounds[label] = [0]
            return
        found = recognise_recurrence(next(iter(self.facts.values())).df.sparkSession, self.program, group) if self.facts else None
        if isinstance(found, Stepping):
            base = self._all_rules(found.predicate, [r for r in rules if r is not found.rule])
            if base is not None and base.repeats is None:
                self._repeat(found.predicate, base, PatternRelation(base, found.by * self.timeline.scale, 0, ((f"c{found.place}", (found.a, found.b)),)))
                self.report.rounds[label] = [0]
                return
        if isinstance(found, Carried) and self._carried(found, rules):
            self.report.rounds[label] = [0]
            return
        late = {a.predicate for r in rules for x in r.literals for a in x.atoms() if a.predicate in self.patterns}
        if late and self.o.horizon:
            # A recursion that reads facts which repeat sees them up to the horizon.
            for p in late:
                r = self.env[p]
                self.env[p] = r.with_df(r.df.unionByName(r.repeats.unroll(*self.o.horizon).df.select(*r.keys, LO, HI)))
        if self.report.kind != "finite" and not self.o.horizon and self._unending(group, rules, label):
            return
        replaced = any(isinstance(c, Aggregate) and r.head and Var(c.name) in r.head.terms for r in rules for c in r.conditions if any(a.predicate in group for x in r.literals for a in x.atoms()))
        for p, r in (self._replacing if replaced else self._rounds)(group, rules, label, self.o.horizon).items():
            self._know(p, r)

    def _repeat(self, p: str, base: TemporalRelation, pattern: PatternRelation) -> None:
        """A predicate that repeats for ever; with a horizon its occurrences up to there."""
        if self.o.horizon:
            self.patterns[p] = pattern
            self.env[p] = pattern.unroll(*self.o.horizon)
            self.report.clipped = True
        else:
            self._know(p, only_pattern(pattern))

    def _carried(self, c: Carried, rules: list[Rule]) -> bool:
        """Totals that are carried on from instant to instant, where all inputs are punctual."""
        inside = {c.total, c.part}
        outside = lambda p: [r for r in self.program.for_head(p) if r not in (c.feed, c.gather)]
        inputs, seeds = self._all_rules(c.part, outside(c.part)), self._all_rules(c.total, outside(c.total))
        if inputs is None or any(a.predicate in inside for p in inside for r in outside(p) for x in r.literals for a in x.atoms()):
            return False
        given = [r for r in (inputs, seeds) if r is not None]
        if any(r.repeats is not None or not punctual(r) for r in given):
            return False
        value, step = f"c{c.place}", c.by * self.timeline.scale
        keys = [k for k in inputs.keys if k != value]
        flat = lambda r: r.df.select(*keys, F.col(value).cast("double").alias(value), F.col(LO).alias("__at")).distinct()
        whole, last = carry_on(flat(inputs), None if seeds is None else flat(seeds.with_df(seeds.df.toDF(*inputs.keys, LO, HI), inputs.keys)), keys, value, c, step)
        shape = lambda df, by=0: inputs.with_df(df.select(*inputs.keys, (F.col("__at") + by).alias(LO), (F.col("__at") + by).alias(HI)))
        steps = ((value, (c.a, c.b)),)
        self._know(c.total, with_repeats(shape(whole), PatternRelation(shape(last), step, 1, steps)))
        fed = lambda df: df.withColumn(value, F.lit(c.a) * F.col(value) + F.lit(c.b))
        parts = _union([inputs.with_df(inputs.df.withColumn(value, F.col(value).cast("double"))), shape(fed(whole.join(last, [*keys, "__at"], "left_anti")), step)])
        self._know(c.part, with_repeats(parts, PatternRelation(shape(fed(last), step), step, 0, steps)))
        return True

    def _unending(self, group: list[str], rules: list[Rule], label: str) -> bool:
        """Recursion by operators alone, several predicates or rules: rounds within a window that grows until
        the last two pattern lengths of it are alike.  The last one becomes the pattern, or, where it is covered
        throughout, an endless fact; and every rule read over the pattern must say nothing that is not said.
        """
        looping = [r for r in rules if any(a.predicate in group for x in r.literals for a in x.atoms())]
        plain = all(len(r.literals) == 1 and not r.conditions and not r.head.span and r.literals[0].atom and not r.literals[0].negated and all(o in ("past", "alwayspast") for o, _ in r.literals[0].ops) for r in looping)
        edges = [e for e in analysis.dependency_graph(self.program) if e.head in group and e.body in group]
        if not plain or any(e.end is None for e in edges):
            return False
        length = analysis.pattern_length(self.program)
        reach = max(e.end for e in edges)
        bases = [b for p in group if (b := self._all_rules(p, [r for r in self.program.for_head(p) if r not in looping])) is not None]
        if any(b.repeats is not None for b in bases):
            return False
        ends = [b.df.where((F.col(LO) > NEG) & (F.col(HI) < POS)).agg(F.min(LO).alias("a"), F.max(HI).alias("b")).first() for b in bases]
        if not any(e["a"] is not None for e in ends):
            return False
        lo, hi = min(e["a"] for e in ends if e["a"] is not None), max(e["b"] for e in ends if e["b"] is not None)
        width = bases[0].timeline.scale * length * max(1, -(-reach // length))
        for grow in (2, 4, 8, 16, 32, 64):
            end = hi + 1 + width * grow
            known = {p: coalesce(r) for p, r in self._rounds(group, rules, label, (lo, end - 1)).items()}
            before = {p: _within(r, end - 2 * width, end - width - 1, width) for p, r in known.items()}
            last = {p: _within(r, end - width, end - 1) for p, r in known.items()}
            if not all(novel(last[p], before[p]).df.isEmpty() and novel(before[p], last[p]).df.isEmpty() for p in group):
                continue
            found = {}
            for p, r in known.items():
                whole = (F.col(LO) <= end - width) & (F.col(HI) >= end - 1)
                rest = last[p].with_df(staged(last[p].df.where(~((F.col(LO) <= end - width) & (F.col(HI) >= end - 1))), "pattern"), coalesced=True)
                rows = r.with_df(r.df.select(*r.keys, LO, F.when(whole, F.lit(POS)).otherwise(F.col(HI)).alias(HI)), coalesced=True)
                found[p] = rows if rest.df.isEmpty() else with_repeats(rows, PatternRelation(rest, width))
            if all(self._said(self.relation(r, {**self.env, **found}), found[r.head.predicate]) for r in looping):
                for p, r in found.items():
                    self._know(p, r)
                return True
        return False

    def _said(self, new: TemporalRelation, known: TemporalRelation) -> bool:
        """Whether what is known, with its pattern, says all of what a rule derives, with its pattern."""
        def fresh(r: TemporalRelation) -> bool:
            left = novel(r, with_repeats(known, None))
            if known.repeats is not None:
                if not left.df.where(F.col(HI) >= POS).isEmpty():
                    return True
                left = admit(left, known.repeats)
            return not left.df.isEmpty()

        if fresh(with_repeats(new, None).with_df(new.df.toDF(*known.keys, LO, HI), known.keys)):
            return False
        if new.repeats is None:
            return True
        q = new.repeats
        far = common_period([q.period, known.repeats.period]) if known.repeats is not None else q.period
        end = q.base.df.agg(F.max(HI).alias("b")).first()["b"]
        some = q.unroll(NEG // 4, (end or 0) + 2 * far)
        return not fresh(some.with_df(some.df.toDF(*known.keys, LO, HI), known.keys))

    def _typed(self, group: list[str], known: dict[str, TemporalRelation | None]) -> dict[str, TemporalRelation]:
        """Empty relations for predicates without base facts; their columns are those that their rules would give."""
        known = dict(known)
        while missing := [p for p in group if known[p] is None]:
            for p in missing:
                for r in self.program.for_head(p):
                    read = {a.predicate for x in r.literals for a in x.atoms()}
                    if all(known.get(q) is not None for q in read if q in group):
                        got = self.relation(r, {**self.env, **{q: v for q, v in known.items() if v is not None}})
                        known[p] = got.with_df(got.df.limit(0), coalesced=True)
                        break
                if known[p] is not None:
                    break
            else:
                raise RuleError(f"{', '.join(missing)} have no base facts from which their columns could be known")
        return known

    def _starts(self, group: list[str], limit) -> dict[str, TemporalRelation]:
        known = {}
        for p in group:
            exit_rules = [r for r in self.program.for_head(p) if not any(a.predicate in group for x in r.literals for a in x.atoms())]
            start = self._all_rules(p, exit_rules)
            if start is not None and start.repeats is not None:
                raise RuleError(f"{p} repeats for ever and is recursive: state a horizon")
            known[p] = self._clip(coalesce(start), limit) if start is not None else None
        return self._typed(group, known)

    def _rounds(self, group: list[str], rules: list[Rule], label: str, limit: tuple[int, int] | None) -> dict[str, TemporalRelation]:
        """A predicate is a list of tables, of which each round adds one; the round is the join of what the last one
        added with the rest of a rule's body, and one sweep that keeps what is new."""
        first = self._starts(group, limit)
        looping = [r for r in rules if any(a.predicate in group for x in r.literals for a in x.atoms())]
        parts, fixed = self._static_parts(looping, group)
        if (solved := self._by_slices(group, first, looping, parts, fixed, label)) is not None:
            return solved
        tables = {p: [staged(r.df.select(*r.keys, LO, HI), p)] for p, r in first.items()}
        delta = {p: first[p].with_df(tables[p][0], coalesced=True) for p in group}
        self.report.rounds[label] = counts = []
        known = lambda p: first[p].with_df(together(tables[p]), coalesced=len(tables[p]) == 1)
        linear = self.o.ahead > 1 and self.o.strategy != "naive" and all(self._one_step(r, group) for r in looping)
        size, whole = 1, 0
        for _ in range(self.o.max_rounds):
            env = {**self.env, **fixed, **{p: known(p) for p in group}}
            derived: dict[str, list[TemporalRelation]] = {p: [] for p in group}

            def step(source: dict[str, TemporalRelation], env=env) -> dict[str, list[TemporalRelation]]:
                env = {**env, **{f"new {p}": source[p] for p in source}}
                out: dict[str, list[TemporalRelation]] = {p: [] for p in group}
                for r in looping:
                    spots = [i for i, x in enumerate(r.literals) if not x.negated and any(a.predicate in group for a in x.atoms())]
                    p = r.head.predicate
                    if self.o.strategy == "naive" or not self._by_delta(r, group):
                        out[p].append(self.relation(r, env, None, parts[id(r)]))
                        continue
                    for i in spots:
                        if r.literals[i].atom.predicate in source:
                            out[p].append(self.relation(r, env, {i: f"new {r.literals[i].atom.predicate}"}, parts[id(r)]))
                return out

            shaped = lambda p, made: first[p].with_df(made.df.toDF(*first[p].keys, LO, HI))
            derived = step(delta)
            if linear and 8 * size < whole:
                # Little is new: steps from what one step derives, merged, spare rounds over all that is known.  What they
                # derive once more is at most what is known, so a round costs no more than its steps over everything.
                one = derived
                for _ in range(self.o.ahead - 1):
                    one = step({p: coalesce(shaped(p, _union(v))) for p, v in one.items() if v})
                    for p, v in one.items():
                        derived[p] += v
            added, fresh = 0, {}
            for p in group:
                if not derived[p]:
                    fresh[p] = delta[p].with_df(delta[p].df.limit(0), coalesced=True)
                    continue
                made = _union(derived[p])
                table = staged(novel(self._clip(made.with_df(made.df.toDF(*first[p].keys, LO, HI), first[p].keys), limit), known(p)).df, p)
                n = table.count()
                added += n
                fresh[p] = first[p].with_df(table, coalesced=True)
                if n:
                    tables[p].append(table)
                else:
                    forget(table)
                    fresh[p] = first[p].with_df(table.sparkSession.createDataFrame([], table.schema), coalesced=True)
            delta = fresh
            size, whole = added, whole + added
            counts.append(added)
            if not added:
                break
            for p in group:
                if len(tables[p]) > self.o.merge_every:
                    # The last table is what the next round reads as new.
                    old = tables[p][:-1]
                    tables[p] = [staged(coalesce(first[p].with_df(together(old)), force=True).df, p), tables[p][-1]]
                    forget(*old)
        else:
            raise RuleError(f"{label} did not end within {self.o.max_rounds} rounds; its model is {self.report.kind}: state a horizon")
        out = {}
        for p in group:
            out[p] = first[p].with_df(staged(coalesce(known(p), force=True).df, p), coalesced=True)
            forget(*tables[p])
        forget(*(r.df for r in fixed.values()))
        return out

    def _by_slices(self, group, first, looping, parts, fixed, label) -> dict[str, TemporalRelation] | None:
        """The fixpoint of one predicate whose rules are joins of it, as it is at the same time, with one part each."""
        if len(group) != 1 or self.o.strategy == "naive" or not self.o.slice_rows:
            return None
        p, base = group[0], first[group[0]]
        steps, tables = [], []
        for r in looping:
            spots = [i for i, x in enumerate(r.literals) if any(a.predicate == p for a in x.atoms())]
            if len(spots) != 1 or len(parts[id(r)]) != 1 or r.head.span or len(base.keys) > 2:
                return None
            x, part = r.literals[spots[0]], parts[id(r)][0]
            terms = x.atom.terms if x.atom else ()
            own = [t.name for t in terms if isinstance(t, Var) and t.name != "_"]
            rest = [c for c in r.conditions if c not in part.conditions]
            heads = [t.name for t in r.head.terms if isinstance(t, Var)]
            if x.negated or x.ops or x.binary or x.atom.span or rest or part.negated or len(part.literals) + 1 != len(r.literals) or len(heads) != len(r.head.terms):
                return None
            if len(set(own)) != len(own) or any(not isinstance(t, Var) for t in terms):
                return None
            place = {t.name: i for i, t in enumerate(terms)}
            s = fixed[part.name]
            kinds = [base.df.schema[k].dataType for k in base.keys]
            equal = tuple((place[v], v) for v in part.variables if v in place and v in own)
            head = tuple(("known", place[v]) if v in own else ("part", v) for v in heads)
            if any(kinds[i] != s.df.schema[v].dataType for i, v in equal) or any(kinds[i] != (kinds[c] if side == "known" else s.df.schema[c].dataType) for i, (side, c) in enumerate(head)):
                return None
            steps.append(Step(equal, head))
            tables.append(s.df)
        start = staged(base.df.select(*base.keys, LO, HI), p)
        cut = slicing([start, *tables], 20_000, self.o.slice_rows)
        if cut is None:
            forget(start)
            return None
        out = staged(solve_slices(start, tables, list(base.keys), steps, cut), p)
        turns = {r["__turn"]: r["n"] for r in out.groupBy("__turn").agg(F.count(F.lit(1)).alias("n")).collect()}
        self.report.rounds[label] = [turns.get(i, 0) for i in range(1, max(turns, default=0) + 2)]
        done = staged(coalesce(base.with_df(out.select(*base.keys, LO, HI)), force=True).df, p)
        forget(start, out, *(r.df for r in fixed.values()))
        return {p: base.with_df(done, coalesced=True)}

    def _by_delta(self, rule: Rule, group: list[str]) -> bool:
        """Whether what a round adds is all that a rule need read of the recursion."""
        mine = [x for x in rule.literals if not x.negated and any(a.predicate in group for a in x.atoms())]
        return all(x.atom is not None and not any(o.startswith("always") for o, _ in x.ops) for x in mine) and not any(isinstance(c, Aggregate) for c in rule.conditions)

    def _one_step(self, rule: Rule, group: list[str]) -> bool:
        """Whether a rule reads the recursion once, so that several steps may follow each other without what is known."""
        return self._by_delta(rule, group) and sum(a.predicate in group for x in rule.literals for a in x.atoms()) == 1

    def _replacing(self, group: list[str], rules: list[Rule], label: str, limit) -> dict[str, TemporalRelation]:
        """Rounds for aggregates whose value is in the head: what a round derives stands instead of what the last one did,
        so smaller sums of fewer contributors do not stay."""
        now = self._starts(group, limit)
        now = {p: r.with_df(staged(r.df.select(*r.keys, LO, HI), p), coalesced=True) for p, r in now.items()}
        looping = [r for r in rules if any(a.predicate in group for x in r.literals for a in x.atoms())]
        parts, fixed = self._static_parts(looping, group)
        exits = {p: [self.relation(r) for r in self.program.for_head(p) if r not in looping] + ([_numbered(self.facts[p])] if p in self.facts else []) for p in group}
        self.report.rounds[label] = counts = []
        sign = lambda r: tuple(r.df.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64(*r.keys, LO, HI)), F.sum(F.xxhash64(*r.keys, LO, HI).cast("decimal(38,0)"))).first())
        last = {p: sign(r) for p, r in now.items()}
        for _ in range(self.o.max_rounds):
            env = {**self.env, **fixed, **now}
            nxt = {}
            for p in group:
                made = _union(exits[p] + [self.relation(r, env, None, parts[id(r)]) for r in looping if r.head.predicate == p])
                made = coalesce(self._clip(made.with_df(made.df.toDF(*now[p].keys, LO, HI), now[p].keys), limit), force=True)
                nxt[p] = made.with_df(staged(made.df, p), coalesced=True)
            signs = {p: sign(r) for p, r in nxt.items()}
            counts.append(sum(s[0] for s in signs.values()))
            forget(*(r.df for r in now.values()))
            now = nxt
            if signs == last:
                forget(*(r.df for r in fixed.values()))
                return now
            last = signs
        raise RuleError(f"{label} did not settle within {self.o.max_rounds} rounds")

    def _static_parts(self, looping: list[Rule], group: list[str]) -> tuple[dict[int, tuple], dict[str, TemporalRelation]]:
        """What does not depend on the recursion, for each rule: literals that share variables are joined, restricted by
        the conditions and negations over their variables, reduced to the variables that are used elsewhere, and kept as tables."""
        parts, fixed = {id(r): () for r in looping}, {}
        if not self.o.static or self.o.strategy == "naive":
            return parts, fixed
        for n, rule in enumerate(looping):
            free = [i for i, x in enumerate(rule.literals) if all(a.predicate not in group and a.predicate != "top" and self.env.get(a.predicate) is not None and self.env[a.predicate].repeats is None for a in x.atoms())]
            named = lambda i, rule=rule: {v for a in rule.literals[i].atoms() for v in a.variables}
            clusters: list[set[int]] = []
            for i in (i for i in free if not rule.literals[i].negated):
                touch = [c for c in clusters if any(named(i) & named(j) for j in c)]
                clusters = [c for c in clusters if c not in touch] + [set().union({i}, *touch)]
            gathers = any(isinstance(c, Aggregate) for c in rule.conditions)
            own, taken = [], set()
            for c in clusters:
                bound = set().union(*(named(i) for i in c))
                minus = {i for i in free if rule.literals[i].negated and named(i) and named(i) <= bound and i not in taken}
                taken |= minus
                ready = tuple(k for k in rule.conditions if isinstance(k, Compare) and k.variables and k.variables <= bound)
                inner = Rule(None, tuple(rule.literals[i] for i in sorted(c | minus)), ready, rule.text)
                r = self.relation(inner)
                used = {t.name for t in (*rule.head.terms, *rule.head.span) if isinstance(t, Var)} | {v for j in range(len(rule.literals)) if j not in c | minus for v in named(j)}
                used |= {v for k in rule.conditions if k not in ready for v in (k.variables if not isinstance(k, Aggregate) else {k.value, *k.contributors})}
                keep = [k for k in r.keys if gathers or k in used]
                if keep != list(r.keys):
                    r = coalesce(r.select(**{k: k for k in keep}))
                name = f"rule {n} part {len(own)} of {'+'.join(group)}"
                fixed[name] = r.with_df(staged(r.df.select(*r.keys, LO, HI), "static"), coalesced=r.coalesced)
                own.append(planner.Part(name, tuple(r.keys), frozenset(c | minus), ready))
            for i in (i for i in free if rule.literals[i].negated and i not in taken):
                r = coalesce(self.relation(Rule(None, (replace(rule.literals[i], negated=False),), (), rule.text)))
                name = f"rule {n} part {len(own)} of {'+'.join(group)}"
                fixed[name] = r.with_df(staged(r.df.select(*r.keys, LO, HI), "static"), coalesced=True)
                own.append(planner.Part(name, tuple(r.keys), frozenset({i}), (), True))
            parts[id(rule)] = tuple(own)
        return parts, fixed

    def _clip(self, r: TemporalRelation, limit: tuple[int, int] | None) -> TemporalRelation:
        if not limit:
            return r
        self.report.clipped = bool(self.o.horizon)
        return _within(r, *limit)

    def query(self, predicate: str, names: list[str] | None = None, between: tuple[int, int] | None = None) -> TemporalRelation:
        """The predicate's tuples with their maximal intervals; ``between`` (ticks) cuts them.

        Without ``between`` a predicate that repeats for ever is answered by its rows and the rows of its pattern, which
        hold again every so many ticks: the last column, ``every``, says how many, and is null for rows that hold once.
        """
        if not self.env:
            self.run()
        r = self.env[predicate]
        pattern = r.repeats if r.repeats is not None else self.patterns.get(predicate)
        s = r.timeline.scale
        if pattern is not None and between:
            r = _union([with_repeats(r, None), pattern.unroll(*(s * x for x in between))])
        elif r.repeats is not None:
            base = pattern.base.df.select(*(F.col(k).alias(n) for k, n in zip(pattern.base.keys, r.keys)), LO, HI, F.lit(pattern.period // s).cast("long").alias("every"))
            base = base.withColumns({LO: F.col(LO) + pattern.n0 * pattern.period, HI: F.col(HI) + pattern.n0 * pattern.period})
            base = base.withColumns({k: F.expr(f"({v[0]!r} * `{k}` + {v[1]!r})").cast(base.schema[k].dataType) for k, v in pattern.steps if pattern.n0})
            r = r.with_df(coalesce(with_repeats(r, None)).df.withColumn("every", F.lit(None).cast("long")).select(*r.keys, "every", LO, HI).unionByName(base), (*r.keys, "every"), True)
            names = [*names, "every"] if names else None
        if between:
            r = _within(r, s * between[0], s * between[1])
        if names:
            r = r.select(**dict(zip(names, r.keys)))
        return coalesce(r)

    def query_span(self, predicate: str, between: tuple[int, int], names: list[str] | None = None) -> TemporalRelation:
        """As ``query`` with ``between``, but base facts outside what the answer can depend on are filtered at the scans."""
        from .planner import input_span, within_span

        spans = input_span(self.program, predicate, between)
        facts = {p: within_span(r, spans.get(p, (None, None))) for p, r in self.facts.items()}
        return Engine(self.program, facts, self.o).query(predicate, names, between)

    def violations(self) -> list[tuple[str, TemporalRelation]]:
        """For every constraint the instances of its body that hold."""
        if not self.env:
            self.run()
        return [(r.text, coalesce(self.relation(r))) for r in self.program.rules if not r.head]

    def explain(self, predicate: str, values: tuple, at: int, most: int = 20, depth: int = 1) -> list[dict]:
        """Derivations of a fact at a tick: the rule, its body's values, how many there are in all (``of``), and with
        ``depth`` above 1 the derivations of the body's derived facts (``parents``).

        Each rule shows its first ``most`` instances in order of their values.  Facts of recursive predicates have parents
        that hold as well, not always earlier ones.
        """
        if not self.env:
            self.run()
        out = []
        for r in self.program.for_head(predicate):
            bound = {t.name: v for t, v in zip(r.head.terms, values) if isinstance(t, Var)}
            if any(not isinstance(t, (Var, Fresh)) and t != v for t, v in zip(r.head.terms, values)):
                continue
            body = self.relation(Rule(None, r.literals, tuple(c for c in r.conditions if not isinstance(c, Aggregate)), r.text))
            cell = at * body.timeline.scale
            if body.repeats is not None:
                body = _union([with_repeats(body, None), body.repeats.unroll(cell, cell)])
            hit = body.df.where((F.col(LO) <= cell) & (F.col(HI) >= cell))
            for k, v in bound.items():
                if k in body.keys:
                    hit = hit.where(F.col(k) == F.lit(v))
            hit = hit.select(*body.keys).distinct()
            n = hit.count()
            for x in hit.orderBy(*body.keys).limit(most).collect() if n else []:
                row = {"rule": r.text.strip(), "of": n, **{k: x[k] for k in body.keys}}
                if depth > 1:
                    heads = self.program.heads()
                    row["parents"] = [
                        {"predicate": a.predicate, "from": self.explain(a.predicate, tuple(x[t.name] if isinstance(t, Var) else t for t in a.terms), at, most, depth - 1)}
                        for y in r.positive if y.atom and not y.ops for a in [y.atom] if a.predicate in heads and not a.span and all(not isinstance(t, Var) or t.name in body.keys for t in a.terms)
                    ]
                out.append(row)
        return out


def _reach(x: Literal) -> int | None:
    """How many ticks away from an instant a literal looks; None without a bound."""
    own = [r.hi for _, r in x.ops]
    if x.binary:
        parts = [_reach(x.left), _reach(x.right), x.range.hi]
        own += [None if any(p is None for p in parts) else max(parts[0], parts[1]) + parts[2]]
    return None if any(v is None for v in own) else sum(own)


def placements(program: str, facts: dict[str, TemporalRelation], predicate: str) -> dict[str, TemporalRelation]:
    """The same query under every placement of merges, to be compared."""
    return {p: Engine(program, facts, Options(placement=p)).query(predicate) for p in ("minimal", "earliest", "always")}


def to_temporal(df: DataFrame, keys, start: str, end: str, timeline: Timeline = DAYS) -> TemporalRelation:
    """Wrap: interval columns become the interval of the facts."""
    from ..model import relation

    return relation(df, keys, start, end, timeline)


def to_plain(r: TemporalRelation) -> DataFrame:
    """Unwrap: the interval becomes ordinary columns."""
    return r.to_df()
