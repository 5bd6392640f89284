"""Maintained models against rebuilt ones, and the known traps."""

import random

import pytest

from chronomill.operators import intervals as iv
from chronomill.plans import maintain as mt
from chronomill.plans import periodic as pr
from chronomill.plans.evaluate import ATOM, Evaluator, bounds
from chronomill.plans.rules import parse_program
from chronomill.plans.workloads import EXAMPLE
from chronomill.sources.store import facts_of, no_facts


def rows(df):
    return sorted((r["pred"], r["a0"], r["lo"], r["hi"]) for r in df.collect())


def test_worked_example(spark):
    p = parse_program(EXAMPLE)
    explicit = facts_of(spark, [("r", [i], 0, 1) for i in range(4)])
    stats = mt.StageStats()
    pm = mt.rebuild(p, explicit, stats=stats)
    assert pm.left is None
    assert pm.right.length == 10
    assert rows(pr.expanded(pm, 0, 100)) == sorted(("r", str(i), 20 * j, min(100, 20 * j + 2)) for i in range(4) for j in range(6))
    target, out, update = mt.maintain(p, explicit, pm, facts_of(spark, [("r", [0], 0, 1)]), facts_of(spark, [("r", [9], 0, 1)]))
    assert rows(pr.expanded(out, 0, 60)) == sorted(("r", str(i), 20 * j, min(60, 20 * j + 2)) for i in (1, 2, 3, 9) for j in range(4))
    assert mt.is_saturated(p, target, out)
    # What the search compares does not grow with the number of entities.
    assert update.stages["retract"].compared <= stats.compared


def test_explicit_survivor(spark):
    p = parse_program("b(x) :- a(x).")
    explicit = facts_of(spark, [("a", [1], 0, 0), ("b", [1], 0, 0)])
    _, out, _ = mt.maintain(p, explicit, mt.rebuild(p, explicit), facts_of(spark, [("a", [1], 0, 0)]), no_facts(spark))
    assert rows(out.core) == [("b", "1", 0, 0)]


def test_circular_support(spark):
    p = parse_program("q() :- PAST_SOME[0,1] p(). p() :- q().")
    explicit = facts_of(spark, [("p", [], 0, 0)])
    pm = mt.rebuild(p, explicit)
    assert pm.right is not None
    _, out, _ = mt.maintain(p, explicit, pm, explicit, no_facts(spark))
    assert out.core.isEmpty()


def test_periodic_algebra(spark):
    a = pr.PeriodicModel(facts_of(spark, [("p", [1], 2 * i, 2 * i) for i in range(7)]), None, pr.Period(21, 24))
    b = pr.PeriodicModel(facts_of(spark, [("p", [1], 3 * i, 3 * i) for i in range(3, 9)]), None, pr.Period(43, 48))
    one = pr.PeriodicModel(facts_of(spark, [("p", [1], 31, 31)]))
    at = lambda pm: {r[2] // 2 for r in rows(pr.expanded(pm, 0, 200))}
    x, y = set(range(0, 101, 2)), set(range(9, 101, 3))
    assert at(pr.pm_union(a, b)) == x | y
    assert at(pr.pm_minus(a, b)) == x - y
    assert at(pr.pm_intersect(a, b)) == x & y
    assert at(pr.pm_union(a, one)) == x | {31}
    assert pr.pm_equal(a, pr.pm_union(a, a))
    assert pr.entails(a, "p", [1], 2000, 2000)
    assert not pr.entails(a, "p", [1], 2002, 2002)


RULES = [
    "NEXT_ALL[2,2] p(x) :- p(x). q(x) :- PAST_SOME[0,1] p(x), s(x). p(x) :- q(x).",
    "q(x) :- PAST_ALL[0,1] p(x). NEXT_ALL[1,2] p(x) :- q(x). r(x) :- NEXT_SOME[0,2] q(x).",
]


@pytest.mark.parametrize("n", range(len(RULES)))
def test_maintained_equals_rebuilt(spark, n):
    p, rng = parse_program(RULES[n]), random.Random(n)
    some = lambda k: [(rng.choice("ps"), [rng.randrange(2)], t := rng.randrange(5), t + rng.randrange(2)) for _ in range(k)]
    start = some(5)
    explicit = facts_of(spark, start)
    removed, added = facts_of(spark, start[:2] + some(1)), facts_of(spark, some(2))
    pm = mt.rebuild(p, explicit)
    for options in (mt.Options(), mt.Options(propagate="later", chain=1)):
        target, out, _ = mt.maintain(p, explicit, pm, removed, added, options)
        assert mt.agree(p, target, out)


def test_retract_covers_what_is_lost(spark):
    p = parse_program("c(x) :- a(x), b(x). d(x) :- PAST_SOME[0,2] c(x).")
    explicit = facts_of(spark, [("a", [1], 0, 4), ("b", [1], 2, 6)])
    pm = mt.rebuild(p, explicit)
    gone = mt.retract(p, pm, facts_of(spark, [("a", [1], 2, 2)]), bounds(explicit), mt.Options(), mt.StageStats())
    left = iv.sweep(iv.coalesced(explicit, ATOM), facts_of(spark, [("a", [1], 2, 2)]), "minus", ATOM)
    lost = pr.pm_minus(pm, mt.rebuild(p, left))
    assert pr.pm_minus(lost, gone).core.isEmpty()
    assert pr.pm_minus(gone, pm).core.isEmpty()


def test_save_and_load(spark, tmp_path):
    pm = pr.PeriodicModel(facts_of(spark, [("p", [1], 0, 2)]), None, pr.Period(1, 4))
    pr.save_model(pm, str(tmp_path / "m"), 3)
    got = pr.load_model(spark, str(tmp_path / "m"))
    assert got.right == pm.right
    assert rows(got.core) == rows(pm.core)


def test_top_and_constants(spark):
    p = parse_program("a(x) :- b(x, 'k'), TOP. c(x) :- b(x, x).")
    out = Evaluator(p).applied(facts_of(spark, [("b", [1, "k"], 0, 1), ("b", [2, 2], 3, 4)]))
    assert rows(out) == [("a", "1", 0, 2), ("c", "2", 6, 8)]


def test_updates_only_take_what_shares_their_first_constant(spark, monkeypatch):
    """Rules about one thing each: what an update works on has the constants of the update only, small or not."""
    program = parse_program("NEXT_ALL[2,2] p(u) :- p(u).  NEXT_ALL[3,3] q(u) :- q(u).  s(u) :- p(u), q(u).")
    assert program.keyed() and not parse_program("z(n) :- h(u), l(u,n).").keyed()
    explicit = facts_of(spark, [(x, [k], k % 3, k % 3) for k in range(6) for x in "pq"])
    pm = mt.rebuild(program, explicit)
    seen, inner = [], mt._maintain

    def watched(program, explicit, few, *rest):
        seen.append({r["a0"] for r in few.core.select("a0").distinct().collect()})
        return inner(program, explicit, few, *rest)

    monkeypatch.setattr(mt, "_maintain", watched)
    fresh = None
    gone, new = facts_of(spark, [("p", [1], 1, 1), ("q", [2], 2, 2)]), facts_of(spark, [("p", [2], 1, 1)])
    for bound in (20_000, 0):
        monkeypatch.setattr(mt.small, "SMALL", bound)
        monkeypatch.setattr(mt.small.fetched, "__defaults__", (bound,))
        target, out, _ = mt.maintain(program, explicit, pm, gone, new)
        assert isinstance(out, mt.Patched) == (bound > 0)
        fresh = fresh or mt.rebuild(program, target)
        assert pr.pm_equal(out, fresh)
    assert seen == [{"1", "2"}] * 2
