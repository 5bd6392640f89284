"""Cell codes: instants and open gaps of a uniform time grid as integers.

Instant t is cell 2t and the open gap (t, t + 1) is cell 2t + 1, so an interval with open or closed ends is an
inclusive range of cells (lo, hi), empty if lo > hi, and neighbours meet when next.lo <= hi + 1.
The same formulas serve integers and Spark columns.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Range:
    """A non-negative bounded range of distances, as cells."""

    lo: int
    hi: int

    @property
    def upper(self) -> int:
        """Right end in grid units."""
        return (self.hi + 1) // 2

    @property
    def has_zero(self) -> bool:
        return self.lo == 0


def encode(start: int, end: int, start_open: bool = False, end_open: bool = False) -> tuple[int, int]:
    return 2 * start + start_open, 2 * end - end_open


def start_of(lo):
    """Grid value at or before a lower cell."""
    return F.floor(lo / 2).cast("long") if isinstance(lo, Column) else lo // 2


def end_of(hi):
    return F.floor((hi + 1) / 2).cast("long") if isinstance(hi, Column) else (hi + 1) // 2


def _odd(x):
    return F.pmod(x, F.lit(2)) if isinstance(x, Column) else x % 2


def dilated(lo, hi, r: Range):
    """Cells from which some cell of (lo, hi) lies back within r: the interval moved forward and widened."""
    return lo + r.lo - (_odd(lo) * (r.lo % 2)), hi + r.hi + (_odd(hi) * (r.hi % 2))


def eroded(lo, hi, r: Range):
    """Cells whose whole range r back lies in (lo, hi)."""
    near, far = start_of(r.lo), end_of(r.hi)
    first, last = start_of(lo) + far, end_of(hi) + near
    return 2 * first + _odd(lo) * (1 - r.hi % 2), 2 * last - _odd(hi) * (1 - r.lo % 2)


def mirrored(function, lo, hi, r: Range):
    """The same towards the future: on the reflected time line."""
    a, b = function(-hi, -lo, r)
    return -b, -a


def closure(lo, hi):
    """The interval with its boundary instants."""
    return lo - _odd(lo), hi + _odd(hi)


def rendered(lo: str = "lo", hi: str = "hi", scale: int = 1) -> list[Column]:
    """start_t, start_open, end_t, end_open of cell columns."""
    a, b = F.col(lo), F.col(hi)
    unit = lambda x: x if scale == 1 else x / scale
    return [unit(start_of(a)).alias("start_t"), (_odd(a) == 1).alias("start_open"), unit(end_of(b)).alias("end_t"), (_odd(b) == 1).alias("end_open")]
