"""Cell algebra against dense time: intervals over quarter instants."""

from fractions import Fraction
from itertools import product

import pytest

from chronomill.functions import cells
from chronomill.functions.cells import Range

POINTS = [Fraction(i, 4) for i in range(-40, 41)]


def has(x, lo, hi):
    """Whether an instant lies in a cell range."""
    cell = 2 * int(x) if x.denominator == 1 else 2 * (x.numerator // x.denominator) + 1
    return lo <= cell <= hi


INTERVALS = [c for s, e, a, b in product(range(3), range(3), (0, 1), (0, 1)) if s <= e and (c := cells.encode(s, e, a, b))[0] <= c[1]]
RANGES = [Range(*c) for c in INTERVALS]


@pytest.mark.parametrize("r", RANGES, ids=str)
def test_dilation_and_erosion_mean_some_and_all(r):
    offsets = [d for d in POINTS if d >= 0 and has(d, r.lo, r.hi)]
    for lo, hi in INTERVALS:
        a, b = cells.dilated(lo, hi, r)
        c, d = cells.eroded(lo, hi, r)
        e, f = cells.mirrored(cells.dilated, lo, hi, r)
        g, h = cells.mirrored(cells.eroded, lo, hi, r)
        for x in [Fraction(i, 2) for i in range(-10, 14)]:
            back, ahead = [has(x - o, lo, hi) for o in offsets], [has(x + o, lo, hi) for o in offsets]
            assert has(x, a, b) == any(back)
            assert has(x, e, f) == any(ahead)
            assert has(x, c, d) == all(back)
            assert has(x, g, h) == all(ahead)


def test_neighbours_meet():
    assert cells.encode(0, 1, False, True)[1] + 1 == cells.encode(1, 2)[0]
    assert cells.encode(0, 1, False, True)[1] + 1 < cells.encode(1, 2, True)[0]
