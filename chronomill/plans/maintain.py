"""Building a periodic model from explicit facts and maintaining it under removals and additions.

retract finds everything that depends on removed facts, restore what of that still follows from the rest, extend what
follows from additions. All three grow a set of facts in rounds from a delta until the set ends or is seen to repeat.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import intervals as iv
from ..sources.store import fact_columns, no_facts, stored, stored_with, union_all
from .evaluate import ATOM, Evaluator, bounds
from . import small
from .periodic import FAR, Grown, Patched, PeriodicModel, Repeat, aligned, expanded, find_periods, pm_equal, pm_minus, pm_union, settled
from .rules import Program

MAX_ROUNDS = 500
CHAIN = 8
#: Body atoms that a round reads from which on the facts that it has found so far are written once, not planned for each atom.
WRITE_FROM = 5


@dataclass
class StageStats:
    rounds: int = 0
    facts: int = 0
    raw: int = 0
    compared: int = 0
    seconds: float = 0.0


@dataclass
class UpdateStats:
    stages: dict[str, StageStats] = field(default_factory=dict)

    @property
    def seconds(self) -> float:
        return sum(s.seconds for s in self.stages.values())

    def shares(self) -> dict[str, float]:
        total = self.seconds or 1.0
        return {k: s.seconds / total for k, s in self.stages.items()}


@dataclass(frozen=True)
class Options:
    retract: str = "any_derivation"
    propagate: str = "inside"
    grow: str = "any_derivation"
    chain: int = CHAIN
    max_rounds: int = MAX_ROUNDS
    naive: bool = False
    periods: bool = True
    stable: str = "delta"  # "whole": the search looks at the whole model
    #: Keep small deltas at the driver and the changed model as a patch; large updates of programs without recursion are rebuilt.
    adaptive: bool = True

    def mode(self, program: Program) -> str:
        """The retraction test; `auto`: by the whole body where that is safe for the program."""
        return program.retract_mode() if self.retract == "auto" else self.retract


def _metrics(program: Program, span: tuple[int, int]) -> dict:
    """What a round needs to know of its delta: size, predicates, ends before, after and within the data span."""
    lo, hi = F.col("lo"), F.col("hi")
    out = {
        "n": F.count(F.lit(1)), "before": F.max(F.when(hi < span[0], hi)), "after": F.min(F.when(lo > span[1], lo)),
        "lo": F.min("lo"), "hi": F.max("hi"), "touches": F.max(F.when((lo <= span[1]) & (hi >= span[0]), 1)),
    }
    return out | {f"has_{p}": F.max(F.when(F.col("pred") == p, 1)) for p in program.arity}


def spread(program: Program, base: PeriodicModel, seeds: PeriodicModel, span: tuple[int, int], growing: bool, options: Options, stats: StageStats, mode: str, fresh: bool = False) -> PeriodicModel:
    """What depends on seeds, seeds included.

    growing: seeds are new to base and consequences may use what was found before; otherwise seeds are part of base and
    found facts are those of base that use them. fresh: base has no facts, and seeds are stored maximal intervals. Seeds with periods enter by slices that grow each round. A round is one
    job: heads that use the delta, less what is known, written with the figures that steer the next round."""
    began = time.perf_counter()
    depth = program.depth
    ev = Evaluator(program)
    metrics = _metrics(program, span)
    pad = 2 * depth + 2
    reach_of_heads = pad * max(1, options.chain)
    reach = seeds.edges()
    step = 2 * max([2 * depth, *(p.length for p in (base.left, base.right, seeds.left, seeds.right) if p)]) + 2
    endless = bool(seeds.left or seeds.right)
    if fresh:
        delta, state = seeds.core, seeds.core.agg(*[c.alias(k) for k, c in metrics.items()]).first().asDict()
    else:
        delta, state = stored_with(iv.coalesced(expanded(seeds, *reach), ATOM), "delta", metrics)
    known, met = delta, set()
    found: Repeat | None = None
    while True:
        stats.rounds += 1
        stats.raw += state["n"]
        if not state["n"] and not endless:
            found = Repeat(None, None, 0)
            break
        if options.periods and stats.rounds > 1:
            before, after = state["before"], state["after"]
            if endless:
                # A slice that is not examined yet limits the zone like a fact would.
                before = reach[0] - 1 if seeds.left and before is None else before
                after = reach[1] + 1 if seeds.right and after is None else after
            limit = reach if endless else (-FAR, FAR)
            watched = known if options.stable == "delta" else known.unionByName(expanded(base, *_window(known, pad)))
            found = find_periods(watched, depth, span, (before, after, bool(state["touches"])), base.left or seeds.left, base.right or seeds.right, limit)
            if found:
                stats.compared += found.compared
                break
        if stats.rounds > options.max_rounds:
            raise RuntimeError(f"no period within {options.max_rounds} rounds")
        parts, apart, heads, joined = [], [known], None, []
        if state["n"]:
            lo, hi = state["lo"] - pad, state["hi"] + pad
            preds = {p for p in program.arity if state[f"has_{p}"]}
            met |= preds
            # Slices of endless seeds and naive rounds may give any predicate.
            heads = None if endless or options.naive else sorted({r.head_rel.pred for r in program.rules if r.head_rel and program.needs(r) & preds})
            joined = [r for r in program.rules if program.needs(r) & preds and ev.joins_itself(r)]
            ev.dealt(lo, hi)
            near = _near(program, base, known, delta, lo, hi, preds, met, fresh, stats.rounds == 1) if growing and not options.naive else expanded(base, lo, hi)
            if growing:
                if options.naive:
                    # Only atoms with new facts can have longer intervals than before.
                    names = known.select(*ATOM).distinct()
                    longer = iv.coalesced(near.join(names, ATOM, "left_semi").select(*fact_columns()).unionByName(iv.clipped(known, lo, hi)), ATOM)
                    near = near.join(names, ATOM, "left_anti").select(*fact_columns()).unionByName(longer)
                apart.append(expanded(base, state["lo"] - reach_of_heads, state["hi"] + reach_of_heads))
            parts.append(ev.applied(near) if options.naive else ev.affected(near, delta, preds, mode, options.chain, raw=True, exact=not growing, fresh=fresh and stats.rounds == 1 and not endless))
        if endless:
            wider = (reach[0] - (step if seeds.left else 0), reach[1] + (step if seeds.right else 0))
            parts += [expanded(seeds, a, b) for a, b in ((wider[0], reach[0] - 1), (reach[1] + 1, wider[1])) if a <= b]
            reach = wider
        delta, state = stored_with(iv.sweep(union_all(parts), union_all(apart if heads is None else [x.filter(F.col("pred").isin(heads)) for x in apart]), "minus", ATOM, repeated=bool(joined)), "delta", metrics)
        known = known.unionByName(delta)
        if stats.rounds % 8 == 0:
            known = stored(iv.coalesced(known, ATOM), "known")
    core = iv.clipped(iv.coalesced(known, ATOM), found.left.lo if found.left else None, found.right.hi if found.right else None)
    core, counted = stored_with(core, "stage", {"n": F.count(F.lit(1))})
    stats.facts = counted["n"]
    stats.seconds += time.perf_counter() - began
    return PeriodicModel(core, found.left, found.right)


def _near(program: Program, base: PeriodicModel, known: DataFrame, delta: DataFrame, lo: int, hi: int, preds: set[str], met: set[str], fresh: bool, first: bool) -> Grown:
    """base and known within the cells [lo, hi] as maximal intervals, for the rules that read preds; met: the predicates of known.
    Only atoms of known can have longer intervals than in base."""
    rules = [r for r in program.rules if program.needs(r) & preds]
    needed = sorted(set().union(*[program.needs(r) for r in rules]) & met)
    known = (delta if first else known).filter(F.col("pred").isin(needed))
    names = known.select(*ATOM).distinct()
    if not fresh:
        old = expanded(base, lo, hi, lambda df: df.filter(F.col("pred").isin(needed)).join(names, ATOM, "left_semi"))
        longer = iv.coalesced(old.unionByName(iv.clipped(known, lo, hi)), ATOM)
    else:
        # The first delta is coalesced already.
        longer = iv.clipped(known, lo, hi) if first else iv.coalesced(iv.clipped(known, lo, hi), ATOM)
    if sum(len(r.body) for r in rules) >= WRITE_FROM and not (fresh and first):
        longer = stored(longer, "longer")
        names = names if fresh else stored(names, "names")
    return Grown(base, lo, hi, (names, longer), met, not fresh)


def _window(df: DataFrame, pad: int) -> tuple[int, int]:
    lo, hi = bounds(df)
    return lo - pad, hi + pad


def bounded(df: DataFrame) -> PeriodicModel:
    """A finite set of facts as a model."""
    return PeriodicModel(df)


def rebuild(program: Program, explicit: DataFrame, options: Options | None = None, stats: StageStats | None = None, maximal: bool = False) -> PeriodicModel:
    """The model of explicit facts from scratch. maximal: they are stored, as maximal intervals."""
    options, stats = options or Options(), stats if stats is not None else StageStats()
    explicit = explicit if maximal else stored(iv.coalesced(explicit, ATOM), "explicit")
    if explicit.isEmpty():
        return bounded(explicit)
    span = bounds(explicit)
    out = spread(program, bounded(no_facts(explicit.sparkSession)), bounded(explicit), span, True, options, stats, options.grow, fresh=True)
    out.span = span
    return out


def normalised(explicit: DataFrame, removed: DataFrame, added: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Removals that are explicit and not added again; additions that are not explicit yet. Point by point."""
    removed, added = iv.coalesced(removed, ATOM), iv.coalesced(added, ATOM)
    explicit = explicit.join(removed.unionByName(added).select(*ATOM).distinct(), ATOM, "left_semi").select(*fact_columns())
    gone = iv.sweep(iv.sweep(removed, added, "minus", ATOM), explicit, "intersect", ATOM)
    return stored(gone, "removed"), stored(iv.sweep(added, explicit, "minus", ATOM), "added")


def retract(program: Program, pm: PeriodicModel, removed: DataFrame, span: tuple[int, int], options: Options, stats: StageStats) -> PeriodicModel:
    """Everything in the model that has a derivation from removed facts."""
    return spread(program, pm, bounded(removed), span, False, options, stats, options.mode(program))


def still_derivable(program: Program, rest: PeriodicModel, gone: PeriodicModel, survivors: DataFrame) -> PeriodicModel:
    """Facts of gone that are explicit still or follow from rest in one step; beyond a margin of the program's depth
    they repeat as both models do together."""
    pad = 2 * program.depth + 2
    left, right = settled(*aligned(rest, gone), pad)
    g_lo, g_hi = gone.edges()
    lo, hi = (left.lo if left else g_lo), (right.hi if right else g_hi)
    window = stored(expanded(gone, lo, hi), "gone")
    wanted = window.select("pred").distinct()
    rules = tuple(r for r in program.rules if r.head_rel and r.head_rel.pred in {x[0] for x in wanted.collect()})
    near = expanded(rest, lo - pad, hi + pad)
    ev = Evaluator(program)
    ev.dealt(lo - pad, hi + pad)
    heads = [ev.for_atoms(r, near, window) for r in rules]
    out = union_all([*heads, survivors.select(*fact_columns())]).join(window.select(*ATOM).distinct(), ATOM, "left_semi").select(*fact_columns())
    seeds = iv.sweep(iv.clipped(out, lo, hi), window, "intersect", ATOM)
    return PeriodicModel(stored(seeds, "restorable"), left, right)


def restore(program: Program, rest: PeriodicModel, gone: PeriodicModel, explicit: DataFrame, span: tuple[int, int], options: Options, stats: StageStats) -> PeriodicModel:
    """What of gone holds without the removed facts."""
    began = time.perf_counter()
    seeds = still_derivable(program, rest, gone, explicit)
    stats.seconds += time.perf_counter() - began
    if seeds.core.isEmpty():
        return bounded(seeds.core)
    if options.propagate == "later":
        stats.facts = seeds.core.count()
        return seeds
    return spread(program, rest, seeds, span, True, options, stats, options.grow)


def extend(program: Program, pm: PeriodicModel, seeds: PeriodicModel, span: tuple[int, int], options: Options, stats: StageStats) -> PeriodicModel:
    """What seeds, none of which the model has, add to it."""
    return spread(program, pm, seeds, span, True, options, stats, options.grow)


def maintain(program: Program, explicit: DataFrame, pm: PeriodicModel | Patched, removed: DataFrame, added: DataFrame, options: Options | None = None) -> tuple[DataFrame, PeriodicModel | Patched, UpdateStats]:
    """The changed explicit facts, their model, and what each stage did.

    A small update (at most small.SMALL rows in any step) costs what it touches: the results are patches on explicit and
    pm, to be written whole (`kept`) now and then. Others go through distributed frames, or, where that is cheaper, are
    rebuilt (stats without stages then). Where facts only bear on facts with their first constant, all this is done on
    the facts with the constants of the update, taken out of explicit and pm once."""
    options = options or Options()
    if not (options.adaptive and program.keyed()):
        return _maintain(program, explicit, pm, removed, added, options)
    keys = stored(removed.select("a0").unionByName(added.select("a0")).distinct(), "keys")
    own, others = (lambda df, how=how: df.select(*fact_columns()).join(keys, "a0", how).select(*fact_columns()) for how in ("left_semi", "left_anti"))
    few = PeriodicModel(stored(own(pm.core), "own"), pm.left, pm.right, pm.span)
    target, out, stats = _maintain(program, stored(own(explicit), "own"), few, removed, added, options)
    if out is few:
        return explicit, pm, stats
    target = others(explicit).unionByName(target)
    if isinstance(out, Patched):
        try:
            whole = small.patched(pm, [(*a, 0, 0) for a in out.atoms], out.patch)
            whole.span = out.span
            return target, whole, stats
        except small.TooMany:  # together with what pm has been patched with before
            pass
    rest = PeriodicModel(others(pm.core), pm.left, pm.right)
    left, right = aligned(rest, out)
    lo, hi = (left.lo if left else -FAR), (right.hi if right else FAR)
    facts = expanded(rest, lo, hi).unionByName(expanded(out, lo, hi))
    spans = [x for x in (pm.span, out.span) if x]
    return target, PeriodicModel(facts, left, right, (min(a for a, _ in spans), max(b for _, b in spans)) if spans else None).kept("model"), stats


def _maintain(program: Program, explicit: DataFrame, pm: PeriodicModel | Patched, removed: DataFrame, added: DataFrame, options: Options) -> tuple[DataFrame, PeriodicModel | Patched, UpdateStats]:
    """maintain on all facts given."""
    stats = UpdateStats({k: StageStats() for k in ("retract", "restore", "extend")})
    if options.adaptive:
        try:
            return *small.update(program, explicit, pm, removed, added, options, stats), stats
        except small.TooMany:
            stats = UpdateStats({k: StageStats() for k in ("retract", "restore", "extend")})
    removed, added = normalised(explicit, removed, added)
    if options.adaptive and should_rebuild(program, explicit, removed.unionByName(added)):
        target = stored(iv.sweep(iv.sweep(explicit, removed, "minus", ATOM), added, "union", ATOM), "explicit")
        return target, rebuild(program, target, options), stats
    names = removed.select(*ATOM).distinct()
    met = iv.sweep(explicit.join(names, ATOM, "left_semi").select(*fact_columns()), removed, "minus", ATOM)
    left_over = stored(explicit.join(names, ATOM, "left_anti").select(*fact_columns()).unionByName(met), "explicit")
    target = stored(iv.coalesced(left_over.unionByName(added), ATOM), "explicit") if not added.isEmpty() else left_over
    (a, b), (c, d) = bounds(explicit), bounds(target)
    span = (min(a, c), max(b, d))
    later: PeriodicModel | None = None
    if not removed.isEmpty():
        gone = retract(program, pm, removed, span, options, stats.stages["retract"])
        rest = pm_minus(pm, gone).kept("rest")
        back = restore(program, rest, gone, left_over, span, options, stats.stages["restore"])
        if options.propagate == "later" and not back.core.isEmpty():
            pm, later = rest, back
        else:
            pm = pm_union(rest, back).kept("model") if not back.core.isEmpty() else rest
    if not added.isEmpty() or later:
        new = bounded(added)
        if later:
            new = pm_union(later, new) if not added.isEmpty() else later
        new = pm_minus(new, pm).kept("new")
        if not new.core.isEmpty():
            grown = extend(program, pm, new, span, options, stats.stages["extend"])
            pm = pm_union(pm, grown).kept("model")
    return target, pm, stats


def should_rebuild(program: Program, explicit: DataFrame, changed: DataFrame, threshold: float = 0.05) -> bool:
    """Large updates of rule sets without recursion are cheaper to rebuild."""
    return not program.recursive() and changed.count() > threshold * max(1, explicit.count())


def is_saturated(program: Program, explicit: DataFrame, pm: PeriodicModel) -> bool:
    """The model has the explicit facts, and one more application of the rules adds nothing within its core and one
    further copy of each period."""
    pad = 2 * program.depth + 2
    lo, hi = pm.edges()
    lo -= pm.left.cells if pm.left else pad
    hi += pm.right.cells if pm.right else pad
    facts = expanded(pm, lo - pad, hi + pad)
    if not iv.sweep(explicit, facts, "minus", ATOM).isEmpty():
        return False
    new = iv.sweep(Evaluator(program).applied(facts), facts, "minus", ATOM)
    return iv.clipped(new, lo, hi).isEmpty()


def agree(program: Program, explicit: DataFrame, pm: PeriodicModel) -> bool:
    """The accuracy measure: both differences with the rebuilt model are empty."""
    return pm_equal(pm, rebuild(program, explicit))


def round_bound(atoms: int, window_cells: int, period_ends: int) -> str:
    """A bound on rounds from the existence argument, written out as it is doubly exponential."""
    return f"{period_ends} + {window_cells} * {period_ends} * 2^{atoms * window_cells}"


def explain_fact(program: Program, pm: PeriodicModel, pred: str, args: list[str], cell: int) -> DataFrame:
    """Rules (by number) with a body that gives an atom at a cell, and the bindings that do."""
    pad = 2 * program.depth + 2
    facts = expanded(pm, cell - pad, cell + pad)
    ev = Evaluator(program)
    wanted = facts.filter(F.col("pred") == pred)
    for c, x in zip(ATOM[1:], args, strict=False):
        wanted = wanted.filter(F.col(c) == str(x))
    out = None
    for i, r in enumerate(program.rules):
        if r.head_rel and r.head_rel.pred == pred:
            heads = iv.clipped(ev.for_atoms(r, facts, wanted), cell, cell).join(wanted.select(*ATOM).distinct(), ATOM, "left_semi")
            got = heads.select(F.lit(i).alias("rule"), *ATOM, "lo", "hi").distinct()
            out = got if out is None else out.unionByName(got)
    return out if out is not None else no_facts(facts.sparkSession).select(F.lit(0).alias("rule"), "*")
