"""Rule evaluation as DataFrame plans.

A fact frame has pred, a0, a1, a2, lo, hi; a binding frame has one column v_<variable> for each variable, lo and hi.
Facts are kept coalesced: an operator for all instants is right on maximal intervals only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import intervals as iv
from ..sources.store import ARGS, fact_columns, no_facts, union_all
from .rules import Binary, Bottom, Metric, Program, Rel, Rule, Span, Top, Unary, Var, relations, variables

ATOM = ["pred", *ARGS]
#: Stretches of time by which the atoms of a rule that joins its own predicate are dealt.
BUCKETS = 64
#: Words of 64 cells up to which such a rule is joined by words.
WORDS = 128


def v(name: str) -> str:
    return f"v_{name}"


def binding_columns(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c.startswith("v_")]


def leaf(rel: Rel, facts, near: DataFrame | None = None) -> DataFrame:
    """Bindings of a relational atom: constants and repeated variables become filters. facts: a fact frame, or a stretch
    of a model (periodic.Stretch), of which only what the atom asks for is expanded."""
    first: dict[str, str] = {}
    tests = [F.col("pred") == rel.pred]
    for t, a in zip(rel.terms, ARGS, strict=False):
        if not isinstance(t, Var):
            tests.append(F.col(a) == str(t))
        elif t.name in first:
            tests.append(F.col(a) == F.col(first[t.name]))
        else:
            first[t.name] = a
    named = [F.col(a).alias(v(n)) for n, a in first.items()]
    shared = [n for n in first if near is not None and v(n) in near.columns]

    def asked(df: DataFrame) -> DataFrame:
        for t in tests:
            df = df.filter(t)
        # Before periods are copied, so that copies are made of what is near only.
        return df.join(near.select(*[F.col(v(n)).alias(first[n]) for n in shared]), [first[n] for n in shared], "left_semi") if shared else df

    df = asked(facts) if isinstance(facts, DataFrame) else facts.of(asked, rel.pred)
    return df.select(*named, "lo", "hi")


def restricted(df: DataFrame, near: DataFrame | None) -> DataFrame:
    """Rows whose shared variables occur in near."""
    shared = [c for c in binding_columns(df) if near is not None and c in near.columns]
    return df.join(near.select(*shared), shared, "left_semi") if shared else df


class Evaluator:
    """Evaluates metric atoms and rules of a program; time ranges are scaled to the program's grid."""

    def __init__(self, program: Program, whole: tuple[int, int] | None = None) -> None:
        self.program = program
        #: Cells within which TOP holds (evaluation is always on a bounded stretch of time).
        self.whole = whole or (-(1 << 50), 1 << 50)
        #: Cells of the stretches by which rules that join their own predicate are dealt, if they are.
        self.width: int | None = None
        #: Whether the time there is short enough for words.
        self.words = False

    def dealt(self, lo: int, hi: int) -> None:
        """Deal rules that join their own predicate by time within the cells [lo, hi]."""
        self.width, self.words = max(1, (hi - lo) // BUCKETS), hi - lo < iv.WORD * WORDS

    def range(self, span: Span):
        return span.on_grid(self.program.scale)

    def metric(self, m: Metric, facts: DataFrame, near: DataFrame | None = None) -> DataFrame:
        if isinstance(m, Rel):
            return leaf(m, facts, near)
        if isinstance(m, Top):
            return facts.sparkSession.createDataFrame([self.whole], "lo long, hi long")
        if isinstance(m, Bottom):
            return facts.sparkSession.createDataFrame([], "lo long, hi long")
        if isinstance(m, Unary):
            inner = self.metric(m.of, facts, near)
            r = self.range(m.span)
            if m.op.endswith("SOME"):
                return (iv.past_some if m.op == "PAST_SOME" else iv.next_some)(inner, r)
            if not isinstance(m.of, Rel) or len(variables(m.of)) < len(m.of.terms):
                inner = iv.coalesced(inner)
            return (iv.past_all if m.op == "PAST_ALL" else iv.next_all)(inner, r)
        assert isinstance(m, Binary)
        holds = iv.coalesced(self.metric(m.holds, facts, near))
        trigger = self.metric(m.trigger, facts, near)
        return (iv.since if m.op == "SINCE" else iv.until)(holds, trigger, self.range(m.span))

    def touched(self, m: Metric, facts: DataFrame, delta: DataFrame, preds: set[str], exact: bool = True) -> DataFrame | None:
        """Bindings of m over facts with a derivation that uses a point of delta (part of facts); None if there can be none.
        Not exact: bindings near delta that do not use it may come along."""
        if not preds & {r.pred for r in relations(m)}:
            return None
        if isinstance(m, Rel):
            return leaf(m, delta)
        if isinstance(m, Unary):
            inner = self.touched(m.of, facts, delta, preds, exact)
            if inner is None:
                return None
            r = self.range(m.span)
            ahead = m.op.startswith("NEXT")
            reach = (iv.next_some if ahead else iv.past_some)(inner, r)
            if m.op.endswith("SOME"):
                return reach
            full = self.metric(m, facts, near=inner)
            return self._within(full, reach) if exact else full
        assert isinstance(m, Binary)
        r = self.range(m.span)
        carry = iv.until if m.op == "UNTIL" else iv.since
        parts = []
        trigger = self.touched(m.trigger, facts, delta, preds, exact)
        if trigger is not None:
            parts.append(carry(iv.coalesced(self.metric(m.holds, facts, near=trigger)), trigger, r))
        holds = self.touched(m.holds, facts, delta, preds, exact)
        if holds is not None:
            from ..functions.cells import Range

            reach = (iv.next_some if m.op == "UNTIL" else iv.past_some)(holds, Range(0, r.hi))
            full = self.metric(m, facts, near=holds)
            parts.append(self._within(full, reach) if exact else full)
        if not parts:
            return None
        return union_all([p.select(*parts[0].columns) for p in parts])

    @staticmethod
    def _within(full: DataFrame, reach: DataFrame) -> DataFrame:
        """full clipped to the reach of its own variables."""
        on = [c for c in binding_columns(full) if c in reach.columns]
        return iv.overlap_join(full, iv.coalesced(reach.select(*on, "lo", "hi"), on), on)

    def body(self, rule: Rule, facts: DataFrame, near: DataFrame | None = None, first: int | None = None, seed: DataFrame | None = None) -> DataFrame:
        """Natural join of the body atoms on shared variables and common time; with seed, atom `first` is given and the
        others follow in an order that shares variables, restricted to what it binds."""
        left = list(range(len(rule.body)))
        needed = variables(rule.head)
        out = seed
        if out is None:
            first = self._opener(rule)
            out = self.metric(rule.body[first], facts, near)
        left.remove(first)
        while left:
            bound = set(binding_columns(out))
            i = next((i for i in left if {v(x) for x in variables(rule.body[i])} & bound), left[0])
            left.remove(i)
            later = needed.union(*[variables(rule.body[j]) for j in left]) if left else set(needed)
            atom = self.metric(rule.body[i], facts, out if seed is not None else near)
            # Variables that nothing else reads are dropped before the join.
            keep = [c for c in binding_columns(atom) if c in bound or c[2:] in later]
            atom = atom.select(*keep, "lo", "hi")
            atom = atom if len(keep) == len(variables(rule.body[i])) else atom.distinct()
            on = [c for c in keep if c in bound]
            if self.words and self.joins_itself(rule) and all(isinstance(b, Rel) for b in rule.body):
                out = iv.overlap_join_in_words(out, atom, on, [c for c in dict.fromkeys([*binding_columns(out), *keep]) if c[2:] in later])
                continue
            out = iv.overlap_join(out, atom, on, self.width if self.joins_itself(rule) else None)
            out = out.select(*[c for c in binding_columns(out) if c[2:] in later], "lo", "hi")
        return out

    @staticmethod
    def joins_itself(rule: Rule) -> bool:
        """Whether the body joins the head's predicate with itself: few constants then meet at very many times."""
        return rule.head_rel is not None and sum(isinstance(b, Rel) and b.pred == rule.head_rel.pred for b in rule.body) > 1

    @staticmethod
    def _opener(rule: Rule) -> int:
        return max(range(len(rule.body)), key=lambda i: len(variables(rule.body[i])))

    def head(self, rule: Rule, bindings: DataFrame) -> DataFrame:
        """Facts of the head; ranges of nested operators widen the interval one after another."""
        m = rule.head
        while isinstance(m, Unary):
            r = self.range(m.span)
            bindings = (iv.past_some if m.op == "NEXT_ALL" else iv.next_some)(bindings, r)
            m = m.of
        if isinstance(m, Top):
            return no_facts(bindings.sparkSession)
        args = [F.col(v(t.name)) if isinstance(t, Var) else F.lit(str(t)) for t in m.terms]
        args += [F.lit("")] * (len(ARGS) - len(args))
        return bindings.select(F.lit(m.pred).alias("pred"), *[a.alias(n) for a, n in zip(args, ARGS, strict=True)], "lo", "hi")

    def consequence(self, facts: DataFrame) -> DataFrame:
        """facts and what one application of all rules to them gives."""
        return iv.coalesced(union_all([facts.select(*fact_columns()), *[self.head(r, self.body(r, facts)) for r in self.program.rules]]), ATOM)

    def applied(self, facts: DataFrame, rules: tuple[Rule, ...] | None = None) -> DataFrame:
        """Only the heads of one application."""
        found = [self.head(r, self.body(r, facts)) for r in (self.program.rules if rules is None else rules)]
        return iv.coalesced(union_all(found), ATOM) if found else no_facts(facts.sparkSession)

    def affected(self, facts: DataFrame, delta: DataFrame, preds: set[str], mode: str = "any_derivation", chain: int = 1, raw: bool = False, exact: bool = True, fresh: bool = False) -> DataFrame:
        """Heads of rule instances over facts that use a point of delta (part of facts). fresh: delta is all of facts, so
        that every instance does, and a rule is evaluated once instead of once for each atom.

        any_derivation: every such instance. body_change: only where the body fails without delta.
        chain: a rule that only moves its own predicate (`moves`) is followed through so many applications at once. raw: heads may overlap."""
        parts = []
        for rule in self.program.rules:
            seeds = [self.body(rule, facts)] if fresh and self.program.needs(rule) & preds else []
            for j, atom in enumerate([] if fresh else rule.body):
                seed = self.touched(atom, facts, delta, preds, exact)
                if seed is not None:
                    seeds.append(self.body(rule, facts, first=j, seed=seed))
            if not seeds:
                continue
            new = union_all([s.select(*seeds[0].columns) for s in seeds])
            if mode == "body_change":
                rest = iv.sweep(facts.select(*fact_columns()), delta.select(*fact_columns()), "minus", ATOM)
                new = iv.sweep(new, self.body(rule, rest, near=new).select(*new.columns), "minus")
            parts.append(self._chained(rule, new, chain) if chain > 1 and self.moves(rule) else self.head(rule, new))
        if not parts:
            return no_facts(facts.sparkSession)
        return union_all(parts) if raw else iv.coalesced(union_all(parts), ATOM)

    def for_atoms(self, rule: Rule, facts: DataFrame, atoms: DataFrame) -> DataFrame:
        """Heads of a rule over facts, its body restricted to the head constants of atoms."""
        near = leaf(rule.head_rel, atoms).drop("lo", "hi").distinct()
        shared = [c for c in near.columns if c.startswith("v_")]
        return self.head(rule, self.body(rule, facts, near=near if shared else None))

    def moves(self, rule: Rule) -> tuple[int, int, int] | None:
        """How far one application of a rule moves both ends of an interval, and the least change of its width on the
        way, if the rule says of its only atom, under unary operators, what its head says, in whole closed ranges."""
        if len(rule.body) != 1 or rule.head_rel is None:
            return None
        steps, m = [], rule.body[0]
        while isinstance(m, Unary):
            steps.insert(0, (m.op, self.range(m.span)))
            m = m.of
        if m != rule.head_rel or not isinstance(rule.head, Unary):
            return None
        m = rule.head
        while isinstance(m, Unary):
            # What holds at all instants ahead of a fact is the fact seen from behind.
            steps.append(("PAST_SOME" if m.op == "NEXT_ALL" else "NEXT_SOME", self.range(m.span)))
            m = m.of
        low = high = narrowest = 0
        for op, r in steps:
            if r.lo % 2 or r.hi % 2:
                return None
            near, far = (r.lo, r.hi) if op in ("PAST_SOME", "NEXT_ALL") else (r.hi, r.lo)
            sign = 1 if op.startswith("PAST") else -1
            low, high = low + sign * near, high + sign * far
            narrowest = min(narrowest, high - low)
        return low, high, narrowest

    def _chained(self, rule: Rule, bindings: DataFrame, times: int) -> DataFrame:
        """Heads of an application and of up to times - 1 more to each head alone."""
        once = self.head(rule, bindings)
        low, high, narrowest = self.moves(rule)
        n = F.col("_n")
        copies = once.withColumn("_n", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
        wide = F.col("hi") - F.col("lo") + (n - 1) * min(0, high - low) + narrowest >= 0
        return copies.filter((n == 0) | wide).withColumn("lo", F.col("lo") + n * low).withColumn("hi", F.col("hi") + n * high).drop("_n")


def bounds(df: DataFrame) -> tuple[int, int]:
    """Least and greatest cell of a fact frame, both 0 if it is empty."""
    row = df.agg(F.coalesce(F.min("lo"), F.lit(0)), F.coalesce(F.max("hi"), F.lit(0))).first()
    return int(row[0]), int(row[1])


def preds_of(df: DataFrame) -> set[str]:
    return {r[0] for r in df.select("pred").distinct().collect()}  # at most the program's predicates


def satisfied_on(program: Program, facts: DataFrame, lo: int, hi: int) -> bool:
    """One application adds nothing within the cells [lo, hi]."""
    new = iv.sweep(Evaluator(program).applied(facts), facts, "minus", ATOM)
    return iv.clipped(new, lo, hi).isEmpty()


def horizon_model(program: Program, facts: DataFrame, lo: int, hi: int, keep) -> DataFrame:
    """Plain rounds clipped to the cells [lo, hi] up to the fixpoint (exact for rules that only reason forward)."""
    known = keep(iv.clipped(iv.coalesced(facts, ATOM), lo, hi))
    while True:
        more = keep(iv.clipped(Evaluator(program).consequence(known), lo, hi))
        if iv.sweep(more, known, "minus", ATOM).isEmpty():
            return more
        known = more
