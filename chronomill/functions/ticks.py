"""Conversions between table times and grid ticks."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def seconds(c: Column) -> Column:
    """Whole seconds since 1970 of a timestamp (without zone: taken as UTC)."""
    return F.floor(F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), c.cast("timestamp_ntz")) / 1_000_000).cast("long")


def days(c: Column) -> Column:
    return F.unix_date(c.cast("date")).cast("long")


def from_seconds(c: Column) -> Column:
    return F.timestamp_micros(c * 1_000_000).cast("timestamp_ntz")
