"""Rounds of many rules and of rules that join their own predicate, against plain ways."""

from chronomill.operators import intervals as iv
from chronomill.plans import maintain as mt
from chronomill.plans.evaluate import ATOM, Evaluator
from chronomill.plans.rules import parse_program
from chronomill.sources.store import facts_of, no_facts, stored

RULES = """t(x,y) :- e(x,y).
t(x,y) :- t(y,x).
t(x,y) :- t(x,z), t(z,y).
hit(x) :- PAST_SOME[0,2] t(x,x), mark(x).
"""


def test_written_stretches(spark, monkeypatch):
    """Facts found so far are written each round, on an empty base and on a model: as without."""
    program = parse_program("t(x,y) :- e(x,y).\nt(x,y) :- t(x,z), t(z,y).")
    rows = [("e", (i, i + 1), 7 * i, 7 * i + 20) for i in range(3)]
    explicit = stored(iv.coalesced(facts_of(spark, rows), ATOM), "explicit")
    plain = mt.rebuild(program, explicit, mt.Options(naive=True))
    monkeypatch.setattr(mt, "WRITE_FROM", 1)
    pm = mt.rebuild(program, explicit)
    assert iv.sweep(pm.core, plain.core, "symdiff", ATOM).isEmpty()
    less = mt.rebuild(program, facts_of(spark, rows[:2]))
    _, grown, _ = mt.maintain(program, facts_of(spark, rows[:2]), less, no_facts(spark), facts_of(spark, rows[2:]), mt.Options(adaptive=False))
    assert iv.sweep(grown.core, plain.core, "symdiff", ATOM).isEmpty()


def test_first_round_evaluates_a_rule_once(spark):
    program = parse_program(RULES)
    facts = facts_of(spark, [("e", (1, 2), 0, 9), ("t", (1, 2), 0, 9), ("t", (2, 1), 3, 9), ("mark", (1,), 0, 60)])
    ev, preds = Evaluator(program), set(program.arity)
    calls = []
    body = ev.body
    ev.body = lambda rule, *a, **k: calls.append(rule) or body(rule, *a, **k)
    once = ev.affected(facts, facts, preds, raw=True, fresh=True)
    assert len(calls) == len(program.rules)
    assert iv.sweep(once, ev.affected(facts, facts, preds), "symdiff", ATOM).isEmpty()


def test_summed_ends(spark):
    a = facts_of(spark, [("p", (1,), 0, 4), ("p", (1,), 0, 4), ("p", (1,), 4, 9), ("p", (2,), 3, 3)])
    b = facts_of(spark, [("p", (1,), 2, 3), ("p", (1,), 2, 6)])
    for keep in ("minus", "intersect", "union", "symdiff"):
        rows = [sorted(map(tuple, iv.sweep(a, b, keep, ATOM, repeated=r).collect())) for r in (False, True)]
        assert rows[0] == rows[1]
