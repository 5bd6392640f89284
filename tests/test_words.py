"""Rules that join their own predicate: by words of cells as by intervals."""

import random

from chronomill.operators import intervals as iv
from chronomill.plans import maintain as mt
from chronomill.plans.evaluate import ATOM
from chronomill.plans.rules import parse_program
from chronomill.sources.store import facts_of, no_facts, stored, union_all

CLOSURE = """t(x,y) :- e(x,y).
t(x,y) :- t(y,x).
t(x,y) :- t(x,z), t(z,y).
"""


def _rows(spark, columns: str, rng: random.Random):
    rows = []
    for _ in range(60):
        lo = rng.randrange(-300, 300)
        rows.append((rng.randrange(3), rng.randrange(3), lo, lo + rng.choice([0, 0, 1, 5, 62, 63, 64, 65, 127, 128, 300])))
    return spark.createDataFrame(rows, f"{columns}, lo long, hi long")


def _sorted(df) -> list[tuple]:
    return sorted(map(tuple, df.collect()))


def test_words_hold_the_same_cells(spark):
    a = _rows(spark, "x int, k int", random.Random(1))
    again = iv.unworded(iv.worded(a, ["x", "k"], "bits"), ["x", "k"], "bits")
    assert _sorted(iv.coalesced(again)) == _sorted(iv.coalesced(a))


def test_join_in_words(spark):
    rng = random.Random(2)
    a, b = _rows(spark, "x int, k int", rng), _rows(spark, "k int, y int", rng)
    plain = iv.overlap_join(a, b, ["k"]).select("x", "y", "lo", "hi")
    words = iv.overlap_join_in_words(a, b, ["k"], ["x", "y"])
    assert words.count() < plain.count()
    assert _sorted(iv.coalesced(words)) == _sorted(iv.coalesced(plain))


def _graph(spark):
    rng = random.Random(3)
    rows = [("e", (x, y), 40 * i + rng.randrange(30), 40 * i + 60) for i, (x, y) in enumerate((x, y) for x in range(3) for y in range(x))]
    return rows, stored(iv.coalesced(facts_of(spark, rows), ATOM), "explicit")


def test_closure_by_words(spark):
    program, (rows, explicit) = parse_program(CLOSURE), _graph(spark)
    pm = mt.rebuild(program, explicit, maximal=True)
    assert iv.sweep(pm.core, mt.rebuild(program, explicit, mt.Options(naive=True)).core, "symdiff", ATOM).isEmpty()
    target, out, _ = mt.maintain(program, explicit, pm, facts_of(spark, rows[2:]), no_facts(spark), mt.Options(adaptive=False))
    assert mt.agree(program, target, out)


def test_union_by_halves(spark):
    frames = [facts_of(spark, [("p", (i,), i, i)]) for i in range(7)]
    assert [len(union_all(frames[:n]).collect()) for n in range(1, 8)] == list(range(1, 8))
