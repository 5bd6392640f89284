"""Kernels against sets of cells."""

import random

import pytest

from chronomill.functions.cells import Range
from chronomill.operators import intervals as iv


def frame(spark, rows):
    return spark.createDataFrame(rows, "k int, lo long, hi long")


def points(rows):
    return {(k, c) for k, lo, hi in rows for c in range(lo, hi + 1)}


def collected(df):
    return [(r["k"], r["lo"], r["hi"]) for r in df.collect()]


def maximal(rows):
    p = points(rows)
    return all((k, lo - 1) not in p and (k, hi + 1) not in p for k, lo, hi in rows) and len(p) == sum(hi - lo + 1 for _, lo, hi in rows)


@pytest.fixture(scope="module")
def sides(spark):
    rng = random.Random(5)
    make = lambda: [(rng.randrange(4), s, s + rng.randrange(6)) for s in (rng.randrange(40) for _ in range(25))]
    return make(), make()


def test_coalesce(spark, sides):
    for f in (iv.coalesced, lambda d: iv.coalesced_in_slices(d, 7)):
        got = collected(f(frame(spark, sides[0])))
        assert points(got) == points(sides[0])
        assert maximal(got)


@pytest.mark.parametrize("keep", ["union", "intersect", "minus", "symdiff"])
def test_sweep(spark, sides, keep):
    a, b = map(points, sides)
    got = collected(iv.sweep(frame(spark, sides[0]), frame(spark, sides[1]), keep))
    assert points(got) == {"union": a | b, "intersect": a & b, "minus": a - b, "symdiff": a ^ b}[keep]
    assert maximal(got)


def test_buckets_find_what_the_join_finds(spark, sides):
    a, b = (frame(spark, s) for s in sides)
    plain = iv.overlap_join(a, b, ["k"]).collect()
    assert sorted(plain) == sorted(iv.overlap_join(a, b, ["k"], bucket=5).collect())


def test_since_with_zero_and_without(spark):
    holds, trigger = frame(spark, [(1, 0, 10), (2, 5, 5)]), frame(spark, [(1, 4, 4), (1, 30, 30), (2, 5, 5)])
    got = points(collected(iv.since(holds, trigger, Range(0, 4))))
    assert got == {(1, c) for c in range(4, 9)} | {(1, 30), (2, 5), (2, 6)}
    assert points(collected(iv.since(holds, trigger, Range(2, 4)))) == {(1, 6), (1, 7), (1, 8)}


def test_empty(spark):
    none = frame(spark, [])
    assert iv.coalesced(none).isEmpty()
    assert iv.sweep(none, none, "union").isEmpty()
