"""Small updates whose rules find the same points over and over."""

import pytest

from chronomill.plans import maintain as mt
from chronomill.plans import small
from chronomill.plans.periodic import Patched
from chronomill.plans.rules import parse_program
from chronomill.sources.store import facts_of, no_facts, stored

CLOSURE = """t(x,y) :- e(x,y).
t(x,y) :- t(y,x).
t(x,y) :- t(x,z), t(z,y).
"""


def test_repeated_heads_stay_small(spark, monkeypatch):
    """What a small update finds is counted without its repetitions."""
    monkeypatch.setattr(small, "SMALL", 120)
    monkeypatch.setattr(small.fetched, "__defaults__", (120,))
    monkeypatch.setattr(small, "MANY", 1)  # the model is written whole before it is read for restoring
    program = parse_program(CLOSURE)
    rows = [("e", (0, y), 0, 40) for y in range(1, 6)]
    explicit = stored(facts_of(spark, rows), "explicit")
    pm = mt.rebuild(program, explicit, maximal=True)
    target, out, _ = mt.maintain(program, explicit, pm, facts_of(spark, rows[:1]), no_facts(spark))
    assert isinstance(out, Patched)
    assert mt.agree(program, target, out)


def test_unlikely_small_update_is_not_tried(spark, monkeypatch):
    """A delta of which every row is read by many atoms goes to distributed frames before its heads are sought."""
    monkeypatch.setattr(small, "SMALL", 4)
    tried = []
    affected = small.Evaluator.affected
    monkeypatch.setattr(small.Evaluator, "affected", lambda self, *a, **k: tried.append(k.get("raw")) or affected(self, *a, **k))
    program = parse_program("\n".join(f"h{i}(x) :- PAST_SOME[0,2] e(x)." for i in range(8)) + "\nh0(x) :- NEXT_SOME[0,1] h0(x).")
    explicit = stored(facts_of(spark, [("e", (i,), 5 * i, 5 * i + 1) for i in range(20)]), "explicit")
    with pytest.raises(small.TooMany):
        stats = mt.UpdateStats({k: mt.StageStats() for k in ("retract", "restore", "extend")})
        small.update(program, explicit, mt.bounded(explicit), explicit.limit(4), no_facts(spark), mt.Options(), stats)
    assert not tried
