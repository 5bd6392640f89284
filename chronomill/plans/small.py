"""Updates whose changes stay small: deltas are rows at the driver, at most `SMALL` of them, and the stored model is only
probed for the atoms that a delta meets. Whoever uses these functions goes back to distributed frames on `TooMany`."""

from __future__ import annotations

import time
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import intervals as iv
from ..sources.store import fact_columns, no_facts, stored, union_all
from .evaluate import ATOM, Evaluator, bounds
from .periodic import FAR, Patched, Period, PeriodicModel, Repeat, Stretch, common_periods, expanded, find_periods, settled
from .rules import Program, relations

#: Body atoms from which the model that they read is written whole first, not merged with its patch for each.
MANY = 40
#: Rows that a delta, or what is looked up for it, may have at the driver.
SMALL = 20_000

Row = tuple[str, str, str, str, int, int]


class TooMany(Exception):
    """More rows than the driver should hold."""


def fetched(df: DataFrame, bound: int = SMALL) -> list[Row]:
    got = df.select(*fact_columns()).limit(bound + 1).toArrow()
    if got.num_rows > bound:
        raise TooMany
    return list(zip(*(c.to_pylist() for c in got.columns), strict=True))


_SCHEMA = pa.schema([(c, pa.string()) for c in ATOM] + [("lo", pa.int64()), ("hi", pa.int64())])


def frame(spark: SparkSession, rows: Iterable[Row]) -> DataFrame:
    rows = list(rows)
    if not rows:
        return no_facts(spark)
    return spark.createDataFrame(pa.table([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _SCHEMA, strict=True)], schema=_SCHEMA))


def atoms(spark: SparkSession, rows: Iterable[Row]) -> DataFrame:
    """The distinct atoms of rows, to be broadcast."""
    return F.broadcast(frame(spark, {(*r[:4], 0, 0) for r in rows}).select(*ATOM))


def of_atoms(df: DataFrame, rows: list[Row]) -> list[Row]:
    """The rows of df with an atom of rows."""
    return fetched(df.join(atoms(df.sparkSession, rows), ATOM, "left_semi")) if rows else []


# Sets of points, by atom.


def _by_atom(rows: Iterable[Row]) -> dict[tuple, list[tuple[int, int]]]:
    out: dict[tuple, list[tuple[int, int]]] = {}
    for r in rows:
        out.setdefault(r[:4], []).append(r[4:])
    return {a: _joined(x) for a, x in out.items()}


def _joined(parts: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(parts):
        if out and lo <= out[-1][1] + 1:
            out[-1] = (out[-1][0], max(hi, out[-1][1]))
        else:
            out.append((lo, hi))
    return out


def merged(*parts: Iterable[Row]) -> list[Row]:
    """Maximal intervals of all parts together."""
    return [(*a, *x) for a, xs in _by_atom(r for p in parts for r in p).items() for x in xs]


def minus(a: Iterable[Row], b: Iterable[Row]) -> list[Row]:
    out, taken = [], _by_atom(b)
    for atom, xs in _by_atom(a).items():
        cuts = taken.get(atom, [])
        ends = [hi for _, hi in cuts]
        for lo, hi in xs:
            i = bisect_left(ends, lo)
            while lo <= hi and i < len(cuts) and cuts[i][0] <= hi:
                if cuts[i][0] > lo:
                    out.append((*atom, lo, cuts[i][0] - 1))
                lo = cuts[i][1] + 1
                i += 1
            if lo <= hi:
                out.append((*atom, lo, hi))
    return out


def intersect(a: Iterable[Row], b: Iterable[Row]) -> list[Row]:
    a = list(a)
    return minus(a, minus(a, b))


def clipped(rows: Iterable[Row], lo: int, hi: int) -> list[Row]:
    return [(*r[:4], max(r[4], lo), min(r[5], hi)) for r in rows if r[5] >= lo and r[4] <= hi]


@dataclass
class SmallModel:
    """A periodic model of few rows."""

    rows: list[Row]
    left: Period | None = None
    right: Period | None = None

    def edges(self) -> tuple[int, int]:
        lo = min((r[4] for r in self.rows), default=0)
        hi = max((r[5] for r in self.rows), default=0)
        return (self.left.lo if self.left else lo), (self.right.hi if self.right else hi)

    def frames(self, spark: SparkSession) -> PeriodicModel:
        return PeriodicModel(frame(spark, self.rows), self.left, self.right)

    def within(self, lo: int, hi: int) -> list[Row]:
        """All facts within the cells [lo, hi]."""
        out = clipped(self.rows, max(lo, self.left.lo) if self.left else lo, min(hi, self.right.hi) if self.right else hi)
        for p, sign in ((self.right, 1), (self.left, -1)):
            if not p or (hi <= p.hi if sign > 0 else lo >= p.lo):
                continue
            content = clipped(self.rows, p.lo, p.hi)
            first, last = (max(1, (lo - p.hi) // p.cells), (hi - p.lo) // p.cells) if sign > 0 else (max(1, (p.lo - hi) // p.cells), (p.hi - lo) // p.cells)
            if len(content) * (last - first + 1) > 50 * SMALL:
                raise TooMany
            out += [(*r[:4], r[4] + sign * n * p.cells, r[5] + sign * n * p.cells) for n in range(first, last + 1) for r in content]
        return merged(clipped(out, lo, hi))


def combined(a: SmallModel, b: SmallModel, how) -> SmallModel:
    """minus, intersect or merged of two models."""
    left, right = common_periods(a, b)
    lo, hi = (left.lo if left else -FAR), (right.hi if right else FAR)
    return SmallModel(how(a.within(lo, hi), b.within(lo, hi)), left, right)


def restricted(pm: PeriodicModel | Patched, rows: list[Row]) -> SmallModel:
    """The model's facts with an atom of rows."""
    if not rows:
        return SmallModel([])
    if isinstance(pm, Patched):
        wanted = {r[:4] for r in rows}
        inner = SmallModel([r for r in pm.patch.rows if r[:4] in wanted], pm.patch.left, pm.patch.right)
        outer = restricted(pm.base, [r for r in rows if r[:4] not in pm.atoms])
        return combined(inner, outer, merged)
    return SmallModel(of_atoms(pm.core, rows), pm.left, pm.right)


def patched(pm: PeriodicModel | Patched, touched: list[Row], new: SmallModel) -> Patched:
    """pm with the atoms of touched replaced by new: nothing of pm is read or written."""
    base, old, out = (pm.base, pm.patch, set(pm.atoms)) if isinstance(pm, Patched) else (pm, SmallModel([]), set())
    gone = {r[:4] for r in touched}
    kept = SmallModel([r for r in old.rows if r[:4] not in gone], old.left, old.right)
    patch = combined(kept, new, merged) if kept.rows else new
    if len(patch.rows) > SMALL or len(out | gone) > SMALL:
        raise TooMany
    return Patched(base, frozenset(out | gone), patch)


# Growing a set of facts in rounds.


@dataclass
class Delta:
    """What a round found, and what the next one must know of it."""

    rows: list[Row]
    span: tuple[int, int]
    preds: set[str] = field(init=False)

    def __post_init__(self) -> None:
        self.preds = {r[0] for r in self.rows}

    @property
    def lo(self) -> int:
        return min(r[4] for r in self.rows)

    @property
    def hi(self) -> int:
        return max(r[5] for r in self.rows)

    def state(self) -> tuple[int | None, int | None, bool]:
        """Greatest cell before the span, least after it, and whether the span is met."""
        a, b = self.span
        return max((r[5] for r in self.rows if r[5] < a), default=None), min((r[4] for r in self.rows if r[4] > b), default=None), any(r[4] <= b and r[5] >= a for r in self.rows)


class Probe:
    """What a model has of the atoms met so far: each is fetched once, whole."""

    def __init__(self, pm: PeriodicModel | Patched) -> None:
        self.pm, self.spark = pm, pm.spark
        self.met, self.atoms = SmallModel([], pm.left, pm.right), set()

    def meet(self, rows: list[Row]) -> None:
        fresh = [r for r in rows if r[:4] not in self.atoms]
        if fresh:
            got = restricted(self.pm, fresh)
            if (got.left, got.right) != (self.met.left, self.met.right):
                got = combined(self.met, got, merged)
                self.met = got
            else:
                self.met = SmallModel(self.met.rows + got.rows, got.left, got.right)
            self.atoms |= {r[:4] for r in fresh}
            if len(self.met.rows) > 10 * SMALL:
                raise TooMany

    def with_known(self, known: list[Row], lo: int, hi: int) -> Stretch:
        """The model and known as maximal intervals; only atoms of known can have become longer."""
        if not known:
            return Stretch(self.pm, lo, hi)
        self.meet(known)
        own = {r[:4] for r in known}
        longer = merged([r for r in self.met.within(lo, hi) if r[:4] in own], known)
        return Stretch(self.pm, lo, hi, (atoms(self.spark, known), frame(self.spark, longer)))

    def lacks(self, rows: list[Row]) -> list[Row]:
        """What of rows the model does not have."""
        if not rows:
            return rows
        self.meet(rows)
        return minus(rows, self.met.within(min(r[4] for r in rows), max(r[5] for r in rows)))


def spread(program: Program, base: PeriodicModel | Patched, seeds: SmallModel, span: tuple[int, int], growing: bool, options, stats, mode: str) -> SmallModel:
    """What depends on seeds, seeds included: the small form of maintain.spread. A round is one job that finds the heads
    which use the delta, and when growing one that fetches what the model has of their atoms."""
    began, depth, ev, probe = time.perf_counter(), program.depth, Evaluator(program), Probe(base)
    spark = probe.spark
    if options.stable != "delta" or options.naive:
        raise TooMany
    pad = 2 * depth + 2
    reach = seeds.edges()
    left, right = base.left, base.right
    step = 2 * max([2 * depth, *(p.length for p in (left, right, seeds.left, seeds.right) if p)]) + 2
    endless = bool(seeds.left or seeds.right)
    readers = Counter(rel.pred for r in program.rules for m in r.body for rel in relations(m))
    delta = Delta(seeds.within(*reach), span)
    known = list(delta.rows)
    while True:
        stats.rounds += 1
        stats.raw += len(delta.rows)
        if not delta.rows and not endless:
            found = Repeat(None, None, 0)
            break
        if options.periods and stats.rounds > 1:
            before, after, touches = delta.state()
            if endless:
                before = reach[0] - 1 if seeds.left and before is None else before
                after = reach[1] + 1 if seeds.right and after is None else after
            found = find_periods(known, depth, span, (before, after, touches), left or seeds.left, right or seeds.right, reach if endless else (-FAR, FAR))
            if found:
                stats.compared += found.compared
                break
        if stats.rounds > options.max_rounds:
            raise RuntimeError(f"no period within {options.max_rounds} rounds")
        if sum(readers[r[0]] for r in delta.rows) > 5 * SMALL:
            raise TooMany  # each atom that reads a row is likely to give some: not worth the attempt
        new: list[Row] = []
        if delta.rows and any(program.needs(r) & delta.preds for r in program.rules):
            lo, hi = delta.lo - pad, delta.hi + pad
            near = probe.with_known(clipped(known, lo, hi) if growing else [], lo, hi)
            ev.dealt(lo, hi)
            heads = ev.affected(near, F.broadcast(frame(spark, delta.rows)), delta.preds, mode, options.chain, raw=True, exact=not growing)
            if any(ev.joins_itself(r) for r in program.rules if program.needs(r) & delta.preds):
                # Such a rule finds the same points over and over, which only then are more than the driver should hold.
                heads = iv.sweep(heads, frame(spark, known), "minus", ATOM, repeated=True)
            new = fetched(heads)
        if endless:
            wider = (reach[0] - (step if seeds.left else 0), reach[1] + (step if seeds.right else 0))
            for a, b in ((wider[0], reach[0] - 1), (reach[1] + 1, wider[1])):
                if a <= b:
                    new = new + seeds.within(a, b)
            reach = wider
        new = minus(new, known)
        if growing:
            new = probe.lacks(new)
        delta = Delta(new, span)
        known += new
        if len(known) > SMALL:
            raise TooMany
    rows = clipped(merged(known), found.left.lo if found.left else -FAR, found.right.hi if found.right else FAR)
    stats.facts = len(rows)
    stats.seconds += time.perf_counter() - began
    return SmallModel(rows, found.left, found.right)


def restorable(program: Program, rest: Patched, gone: SmallModel, explicit: DataFrame) -> SmallModel:
    """The small form of maintain.still_derivable."""
    spark, pad = explicit.sparkSession, 2 * program.depth + 2
    left, right = common_periods(rest, gone)
    left, right = settled(left, right, pad)
    g_lo, g_hi = gone.edges()
    lo, hi = (left.lo if left else g_lo), (right.hi if right else g_hi)
    window = gone.within(lo, hi)
    preds, atoms_gone = {r[0] for r in window}, frame(spark, window)
    rules = [r for r in program.rules if r.head_rel and r.head_rel.pred in preds]
    if sum(len(r.body) for r in rules) >= MANY:
        rest, atoms_gone = rest.kept("rest"), stored(atoms_gone, "gone")
    near, ev = Stretch(rest, lo - pad, hi + pad), Evaluator(program)
    ev.dealt(lo - pad, hi + pad)
    found = union_all([explicit.select(*fact_columns()), *[ev.for_atoms(r, near, atoms_gone) for r in rules]])
    if any(ev.joins_itself(r) for r in rules):
        own = found.join(atoms(spark, window), ATOM, "left_semi").select(*fact_columns())
        got = fetched(iv.sweep(own, atoms_gone, "intersect", ATOM, repeated=True))
    else:
        got = of_atoms(found, window)
    return SmallModel(intersect(clipped(got, lo, hi), window), left, right)


def update(program: Program, explicit: DataFrame, pm: PeriodicModel | Patched, removed: DataFrame, added: DataFrame, options, stats) -> tuple[DataFrame, Patched | PeriodicModel]:
    """The small form of maintain.maintain: the changed explicit facts and model are patches on what is stored."""
    spark = explicit.sparkSession
    out_rows, in_rows = fetched(removed), fetched(added)
    asked = merged(out_rows, in_rows)
    had = merged(of_atoms(explicit, asked))
    gone, new = intersect(minus(out_rows, in_rows), had), minus(in_rows, had)
    if not gone and not new:
        return explicit, pm
    others = explicit.select(*fact_columns()).join(atoms(spark, asked), ATOM, "left_anti")
    left_over = others.unionByName(frame(spark, minus(had, gone)))
    target = others.unionByName(frame(spark, merged(minus(had, gone), new)))
    span = pm.span or bounds(explicit)
    if new:
        span = (min(span[0], *(r[4] for r in new)), max(span[1], *(r[5] for r in new)))

    def changed(model: PeriodicModel | Patched, by: SmallModel, how) -> Patched:
        out = patched(model, by.rows, combined(restricted(model, by.rows), by, how))
        out.span = span
        return out

    seeds = SmallModel(new)
    if gone:
        lost = spread(program, pm, SmallModel(gone), span, False, options, stats.stages["retract"], options.mode(program))
        pm = changed(pm, lost, minus)
        began = time.perf_counter()
        back = restorable(program, pm, lost, left_over)
        stats.stages["restore"].seconds += time.perf_counter() - began
        if back.rows and options.propagate == "later":
            stats.stages["restore"].facts = len(back.rows)
            seeds = combined(back, seeds, merged) if new else back
        elif back.rows:
            pm = changed(pm, spread(program, pm, back, span, True, options, stats.stages["restore"], options.grow), merged)
    if seeds.rows:
        seeds = combined(seeds, restricted(pm, seeds.rows), minus)
        if seeds.rows:
            pm = changed(pm, spread(program, pm, seeds, span, True, options, stats.stages["extend"], options.grow), merged)
    return target, pm
