"""Periodic models: a finite core with an optional left and right period whose contents repeat for ever."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import intervals as iv
from ..sources.store import ARGS, append_text, fact_columns, latest_text, stored
from .evaluate import ATOM, bounds

FAR = 1 << 60


@dataclass(frozen=True)
class Period:
    """Cells lo..hi of the core that repeat outwards; a right period opens after its first instant, a left one before its last."""

    lo: int
    hi: int

    @property
    def cells(self) -> int:
        return self.hi - self.lo + 1

    @property
    def length(self) -> int:
        """In grid units."""
        return self.cells // 2


@dataclass
class PeriodicModel:
    core: DataFrame
    left: Period | None = None
    right: Period | None = None
    #: Cells within which its explicit facts lie, if known.
    span: tuple[int, int] | None = None

    @property
    def spark(self):
        return self.core.sparkSession

    def edges(self) -> tuple[int, int]:
        """Cells within which the core lies."""
        lo, hi = (0, 0) if self.left and self.right else bounds(self.core)
        return (self.left.lo if self.left else lo), (self.right.hi if self.right else hi)

    def kept(self, name: str = "core") -> PeriodicModel:
        return PeriodicModel(stored(self.core, name), self.left, self.right, self.span)


class Patched:
    """A model of which some atoms were replaced: base without `atoms` (a small set of pred, a0, a1, a2), and patch, a
    small model with those atoms and periods of its own. Merged on read; core, left and right are those of the whole."""

    def __init__(self, base: PeriodicModel, atoms: frozenset, patch) -> None:
        self.base, self.atoms, self.patch = base, atoms, patch
        self._whole: PeriodicModel | None = None
        self._parts: tuple[PeriodicModel, PeriodicModel] | None = None
        self.span: tuple[int, int] | None = base.span

    def parts(self) -> tuple[PeriodicModel, PeriodicModel]:
        from . import small

        if self._parts is None:
            rest = self.base.core
            if self.atoms:
                rest = rest.join(small.atoms(self.spark, [(*a, 0, 0) for a in self.atoms]), ATOM, "left_anti").select(*fact_columns())
            self._parts = PeriodicModel(rest, self.base.left, self.base.right), self.patch.frames(self.spark)
        return self._parts

    @property
    def spark(self):
        return self.base.core.sparkSession

    def whole(self) -> PeriodicModel:
        if self._whole is None:
            rest, patch = self.parts()
            left, right = self._periods()
            lo, hi = (left.lo if left else -FAR), (right.hi if right else FAR)
            self._whole = PeriodicModel(expanded(rest, lo, hi).unionByName(expanded(patch, lo, hi)), left, right, self.span)
        return self._whole

    core = property(lambda self: self.whole().core)
    # The periods of the whole, without expanding it.
    left = property(lambda self: self._periods()[0])
    right = property(lambda self: self._periods()[1])

    def _periods(self) -> tuple[Period | None, Period | None]:
        return aligned(PeriodicModel(self.base.core, self.base.left, self.base.right), self.patch)

    def edges(self) -> tuple[int, int]:
        return self.whole().edges()

    def kept(self, name: str = "core") -> PeriodicModel:
        """The whole model, written anew."""
        return self.whole().kept(name)


class Stretch:
    """The facts of a model within cells, not expanded yet; known: frame of atoms and their facts that stand for the model's."""

    def __init__(self, pm: PeriodicModel | Patched, lo: int, hi: int, known: tuple[DataFrame, DataFrame] | None = None) -> None:
        self.pm, self.lo, self.hi, self.known = pm, lo, hi, known

    @property
    def sparkSession(self):  # noqa: N802
        return self.of(lambda df: df).sparkSession

    def of(self, asked, pred: str | None = None) -> DataFrame:
        """What `asked` (a filter of fact frames by atom, of the predicate pred if given) leaves, expanded."""
        if not self.known:
            return expanded(self.pm, self.lo, self.hi, asked)
        names, facts = self.known
        return expanded(self.pm, self.lo, self.hi, lambda df: asked(df).join(names, ATOM, "left_anti").select(*fact_columns())).unionByName(asked(facts).select(*fact_columns()))

    def select(self, *columns) -> DataFrame:
        return self.of(lambda df: df).select(*columns)


class Grown(Stretch):
    """A stretch of which only the predicates `preds` have known facts: other atoms are read without regard to them.
    base: whether the model has facts at all."""

    def __init__(self, pm: PeriodicModel, lo: int, hi: int, known: tuple[DataFrame, DataFrame], preds: set[str], base: bool) -> None:
        super().__init__(pm, lo, hi, known)
        self.preds, self.base = preds, base

    def of(self, asked, pred: str | None = None) -> DataFrame:
        if not self.base:
            return asked(self.known[1]).select(*fact_columns())
        if pred is not None and pred not in self.preds:
            return expanded(self.pm, self.lo, self.hi, asked)
        return super().of(asked)


def expanded(pm: PeriodicModel | Patched, lo: int, hi: int, asked=None) -> DataFrame:
    """All facts within the cells [lo, hi]; copies of a period are made only where they fall into it. asked: a filter of
    fact frames by atom, applied before."""
    if isinstance(pm, Patched):
        rest, patch = pm.parts()
        return expanded(rest, lo, hi, asked).unionByName(expanded(patch, lo, hi, asked))
    if asked:
        pm = PeriodicModel(asked(pm.core).select(*fact_columns()), pm.left, pm.right)
    parts = [iv.clipped(pm.core, max(lo, pm.left.lo) if pm.left else lo, min(hi, pm.right.hi) if pm.right else hi)]
    if pm.right and hi > pm.right.hi:
        parts.append(_copies(iv.clipped(pm.core, pm.right.lo, pm.right.hi), pm.right.cells, max(1, (lo - pm.right.hi) // pm.right.cells), (hi - pm.right.lo) // pm.right.cells))
    if pm.left and lo < pm.left.lo:
        parts.append(_copies(iv.clipped(pm.core, pm.left.lo, pm.left.hi), -pm.left.cells, max(1, (pm.left.lo - hi) // pm.left.cells), (pm.left.hi - lo) // pm.left.cells))
    if len(parts) == 1:
        return parts[0]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return iv.coalesced(iv.clipped(out, lo, hi), ATOM)


def _copies(df: DataFrame, step: int, first: int, last: int) -> DataFrame:
    return iv.shifted(df.withColumn("_n", F.explode(F.sequence(F.lit(first).cast("long"), F.lit(max(first, last)).cast("long")))), F.col("_n") * step).drop("_n").select(*fact_columns())


def aligned(a: PeriodicModel, b: PeriodicModel, most_cells: int = 10_000_000) -> tuple[Period | None, Period | None]:
    """common_periods, with a bound on their length."""
    left, right = common_periods(a, b)
    if any(p and p.cells > most_cells for p in (left, right)):
        raise OverflowError("the common period is too long; rebuild instead")
    return left, right


def common_periods(a, b) -> tuple[Period | None, Period | None]:
    """Common periods of two models: as long as the least common multiple, from where both repeat; a model without a
    period on a side is empty beyond its core there, and the other's period is moved past that core."""
    if not (a.left or b.left or a.right or b.right):
        return None, None
    right = left = None
    if a.right or b.right:
        n = math.lcm(*[p.cells for p in (a.right, b.right) if p])
        start = max(m.right.lo if m.right else m.edges()[1] + 1 for m in (a, b))
        start += 1 - start % 2
        right = Period(start, start + n - 1)
    if a.left or b.left:
        n = math.lcm(*[p.cells for p in (a.left, b.left) if p])
        end = min(m.left.hi if m.left else m.edges()[0] - 1 for m in (a, b))
        end -= 1 - end % 2
        left = Period(end - n + 1, end)
    return left, right


def settled(left: Period | None, right: Period | None, pad: int) -> tuple[Period | None, Period | None]:
    """The first whole periods past which every rule body sees repeating facts only."""
    shift = lambda p: -(-(2 * pad) // p.cells) * p.cells
    return left and Period(left.lo - shift(left), left.hi - shift(left)), right and Period(right.lo + shift(right), right.hi + shift(right))


def _combined(a: PeriodicModel, b: PeriodicModel, keep: str) -> PeriodicModel:
    left, right = aligned(a, b)
    lo, hi = (left.lo if left else -FAR), (right.hi if right else FAR)
    x, y = expanded(a, lo, hi), expanded(b, lo, hi)
    if keep == "intersect":
        return PeriodicModel(iv.sweep(x, y, keep, ATOM), left, right, a.span)
    # Atoms that b lacks stay as they are.
    names = y.select(*ATOM).distinct()
    met = iv.sweep(x.join(names, ATOM, "left_semi"), y, keep, ATOM)
    return PeriodicModel(x.join(names, ATOM, "left_anti").select(*fact_columns()).unionByName(met), left, right, a.span)


def pm_union(a: PeriodicModel, b: PeriodicModel) -> PeriodicModel:
    return _combined(a, b, "union")


def pm_minus(a: PeriodicModel, b: PeriodicModel) -> PeriodicModel:
    return _combined(a, b, "minus")


def pm_intersect(a: PeriodicModel, b: PeriodicModel) -> PeriodicModel:
    return _combined(a, b, "intersect")


def pm_equal(a: PeriodicModel, b: PeriodicModel) -> bool:
    return pm_minus(a, b).core.isEmpty() and pm_minus(b, a).core.isEmpty()


def folded(pm: PeriodicModel, cell: int) -> int:
    """The cell of the core that says what holds at a cell."""
    if pm.right and cell > pm.right.hi:
        return pm.right.lo + (cell - pm.right.lo) % pm.right.cells
    if pm.left and cell < pm.left.lo:
        return pm.left.hi - (pm.left.hi - cell) % pm.left.cells
    return cell


def entails(pm: PeriodicModel, pred: str, args: list[str], start: int, end: int) -> bool:
    """Whether an atom holds at all cells of start..end."""
    found = expanded(pm, start, end).filter(F.col("pred") == pred)
    for a, x in zip(ARGS, args, strict=False):
        found = found.filter(F.col(a) == str(x))
    return not found.filter((F.col("lo") <= start) & (F.col("hi") >= end)).isEmpty()


def shift_equal(facts: DataFrame | list, first: tuple[int, int], second: tuple[int, int]) -> bool:
    """Whether two windows of cells have the same contents up to shift."""
    if isinstance(facts, list):
        from . import small

        a, b = small.clipped(facts, *first), small.clipped(facts, *second)
        return sorted(small.merged(a)) == sorted((*r[:4], r[4] + first[0] - second[0], r[5] + first[0] - second[0]) for r in small.merged(b))
    a, b = iv.clipped(facts, *first), iv.shifted(iv.clipped(facts, *second), first[0] - second[0])
    return iv.sweep(a, b, "symdiff", ATOM).isEmpty()


# Search for repeating windows.


@dataclass
class Zone:
    """A stretch of cells in which nothing changed last."""

    lo: int
    hi: int


def profile(facts: DataFrame | list, zone: Zone) -> dict[int, int]:
    """Cells at which the set of true atoms changes, with a combined hash of the changes: one row for each such cell."""
    if isinstance(facts, list):
        from . import small

        out: dict[int, int] = {}
        for r in small.merged(small.clipped(facts, zone.lo, zone.hi)):
            for at in (r[4], r[5] + 1):
                out[at] = out.get(at, 0) ^ hash(r[:4])
        return out
    inside = iv.clipped(facts, zone.lo, zone.hi)
    h = F.xxhash64(*ATOM)
    ends = inside.select(F.explode(F.array(F.struct(F.col("lo").alias("at"), h.alias("h")), F.struct((F.col("hi") + 1).alias("at"), h.alias("h")))).alias("e"))
    return {r["at"]: r["x"] for r in ends.select("e.*").groupBy("at").agg(F.bit_xor("h").alias("x")).collect()}


def first_repeat_naive(changes: dict[int, int], zone: Zone, window: int, step: int | None, from_left: bool) -> tuple[int, int] | None:
    """first_repeat by comparing all pairs of cells: its oracle."""
    n = zone.hi - zone.lo + 1
    if n < window + 2:
        return None
    state, row = 0, [0] * n
    for i in range(n):
        state ^= changes.get(zone.lo + i, 0)
        row[i] = state
    if not from_left:
        row.reverse()
    step = step or 2
    for offset in range(step, n - window + 1, step):
        run = 0
        for i in range(n - offset):
            run = run + 1 if row[i] == row[i + offset] else 0
            if run >= window:
                start = i - window + 1
                at = zone.lo + start if from_left else zone.hi - start - window + 1
                # A right window starts at an instant, a left one ends at one.
                if (at % 2 == 0) if from_left else ((at + window - 1) % 2 == 0):
                    return at, offset
    return None


def first_repeat(changes: dict[int, int], zone: Zone, window: int, step: int | None, from_left: bool) -> tuple[int, int] | None:
    """(start, offset) of two windows of `window` cells with equal profiles: the least offset (a multiple of step, if
    given), then the place nearest the data. Windows open on instants for a left period and close on instants for a right.

    Works on stretches between changes: only offsets that move one stretch onto another with the same contents count."""
    n = zone.hi - zone.lo + 1
    step = step or 2
    if n < window + step:
        return None
    # Stretches (first, last, contents) by distance from the data.
    stretches, state = [], changes.get(zone.lo, 0)
    cuts = sorted(c for c, h in changes.items() if zone.lo < c <= zone.hi and h)
    begin = zone.lo
    for c in [*cuts, zone.hi + 1]:
        stretches.append((begin, c - 1, state))
        state ^= changes.get(c, 0)
        begin = c
    stretches = [(a - zone.lo, b - zone.lo, s) for a, b, s in stretches] if from_left else [(zone.hi - b, zone.hi - a, s) for a, b, s in reversed(stretches)]
    firsts = np.array([a for a, _, _ in stretches])
    codes = {s: i for i, s in enumerate(dict.fromkeys(s for _, _, s in stretches))}
    kinds = np.array([codes[s] for _, _, s in stretches])
    parity = zone.lo % 2 if from_left else zone.hi % 2

    def found(offset: int) -> int | None:
        # Ends of stretches of the profile and of the moved one; equal between them or not.
        cut = np.unique(np.concatenate([firsts, firsts - offset, [0, n - offset]]))
        cut = cut[(cut >= 0) & (cut <= n - offset)]
        kind = lambda at: kinds[np.searchsorted(firsts, at, "right") - 1]
        same = kind(cut[:-1]) == kind(cut[:-1] + offset)
        edge = np.flatnonzero(np.diff(np.concatenate([[0], same.astype(np.int8), [0]])))
        for i, j in zip(edge[::2], edge[1::2], strict=True):
            start = int(cut[i]) + (int(cut[i]) + parity) % 2
            if start + window <= int(cut[j]):
                return start
        return None

    offsets: set[int] = set()
    for kind in range(len(codes)):
        own = np.flatnonzero(kinds == kind)
        begins, ends = firsts[own], np.array([stretches[i][1] for i in own])
        if (ends - begins + 1 >= window + step).any():
            offsets.add(step)
        # A change within the window moves onto an equal change; a window without one lies in two long stretches.
        for m in range(len(own)):
            apart = begins[m + 1 :] - begins[m]
            offsets.update(int(x) for x in apart[(apart % step == 0) & (apart > 0)])
            if ends[m] - begins[m] + 1 >= window:
                for lo, hi in zip(begins[m + 1 :] - (ends[m] - window + 1), ends[m + 1 :] - window + 1 - begins[m], strict=True):
                    x = max(step, -(-int(lo) // step) * step)
                    # The least offsets that fit, one for each place of the first window's opening.
                    offsets.update(y for y in (x, x + step) if y <= int(hi) + 1)
    for offset in sorted(offsets):
        if offset <= n - window and (start := found(offset)) is not None:
            return (zone.lo + start if from_left else zone.hi - start - window + 1), offset
    return None


@dataclass
class Repeat:
    left: Period | None
    right: Period | None
    compared: int


def find_periods(facts: DataFrame | list, depth: int, span: tuple[int, int], delta: tuple[int | None, int | None, bool], base_left: Period | None, base_right: Period | None, reach: tuple[int, int]) -> Repeat | None:
    """Periods of a growing set of facts, or None if there is no certificate yet.

    delta: last round's greatest cell before the span, least cell after it, and whether it touches the span;
    base: periods of the model that it grows from (without one, any offset may serve); reach: cells examined so far."""
    before, after, touches = delta
    if touches:
        return None
    window = 4 * depth + 1  # cells of 2 * depth grid units, both instants included
    right = left = None
    compared = 0
    if after is not None:
        lo = max(span[1] + 1, base_right.lo if base_right else span[1] + 1)
        zone = Zone(lo + lo % 2, min(after - 1, reach[1]))
        changes = profile(facts, zone) if zone.hi - zone.lo > window else {}
        compared += len(changes)
        found = first_repeat(changes, zone, window, base_right.cells if base_right else None, True)
        if not found:
            return None
        at, offset = found
        right = Period(at + window, at + window + offset - 1)
        if not shift_equal(facts, (at, at + window - 1), (at + offset, at + offset + window - 1)):
            return None
    if before is not None:
        hi = min(span[0] - 1, base_left.hi if base_left else span[0] - 1)
        zone = Zone(max(before + 1, reach[0]), hi - hi % 2)
        changes = profile(facts, zone) if zone.hi - zone.lo > window else {}
        compared += len(changes)
        found = first_repeat(changes, zone, window, base_left.cells if base_left else None, False)
        if not found:
            return None
        at, offset = found
        left = Period(at - offset, at - 1)
        if not shift_equal(facts, (at, at + window - 1), (at - offset, at - offset + window - 1)):
            return None
    return Repeat(left, right, compared)


def save_model(pm: PeriodicModel, path: str, version: int = 0) -> None:
    """A version folder of facts by predicate; the metadata row that names it is appended last, so that readers find a
    whole version at any time (the folder of the version that is current must not be written again)."""
    pm.core.write.mode("overwrite").partitionBy("pred").parquet(f"{path}/v{version}")
    append_text(pm.core.sparkSession, f"{path}/current", {"version": version, "left": pm.left and [pm.left.lo, pm.left.hi], "right": pm.right and [pm.right.lo, pm.right.hi], "span": pm.span})


def load_model(spark, path: str) -> PeriodicModel:
    meta = latest_text(spark, f"{path}/current")
    core = spark.read.schema("pred string, a0 string, a1 string, a2 string, lo long, hi long").parquet(f"{path}/v{meta['version']}").select(*fact_columns())
    p = lambda x: Period(*x) if x else None
    return PeriodicModel(core, p(meta["left"]), p(meta["right"]), tuple(meta["span"]) if meta.get("span") else None)
