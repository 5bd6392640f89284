"""Kernels on interval relations: frames with key columns and an inclusive range (lo, hi) of cells."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import cells
from ..functions.cells import Range

EDGE = ("lo", "hi")


def keys_of(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c not in EDGE]


def coalesced(df: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Maximal intervals of each key: an interval opens an island unless it meets what came before."""
    keys = keys_of(df) if keys is None else keys
    order = Window.partitionBy(*keys).orderBy("lo", "hi")
    reach = F.max("hi").over(order.rowsBetween(Window.unboundedPreceding, -1))
    opened = df.select(*keys, "lo", "hi", F.when(F.col("lo") <= reach + 1, 0).otherwise(1).alias("_opens"))
    islands = opened.withColumn("_island", F.sum("_opens").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return islands.groupBy(*keys, "_island").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).drop("_island")


def coalesced_in_slices(df: DataFrame, width: int, keys: list[str] | None = None) -> DataFrame:
    """The same for keys with very many intervals: pieces of a key are coalesced by slices of time and stitched."""
    keys = keys_of(df) if keys is None else keys
    cut = df.select(*keys, F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))).alias("_slice"), "lo", "hi")
    clipped = cut.select(*keys, "_slice", F.greatest("lo", F.col("_slice") * width).alias("lo"), F.least("hi", (F.col("_slice") + 1) * width - 1).alias("hi"))
    return coalesced(coalesced(clipped, [*keys, "_slice"]).drop("_slice"), keys)


def sweep(a: DataFrame, b: DataFrame, keep: str, keys: list[str] | None = None, repeated: bool = False) -> DataFrame:
    """Points in a and b (`intersect`), a or b (`union`), a not b (`minus`), or just one (`symdiff`), as maximal intervals.

    Both sides may overlap themselves. All ends of a key are dealt once; running sums take equal cells together. repeated:
    ends are summed by cell before they are dealt, for sides that repeat themselves very often."""
    keys = keys_of(a) if keys is None else keys

    def ends(df: DataFrame, side: int) -> DataFrame:
        steps = F.array(F.struct(F.col("lo").alias("at"), F.lit(1).alias("d")), F.struct((F.col("hi") + 1).alias("at"), F.lit(-1).alias("d")))
        opened = df.select(*keys, F.explode(steps).alias("e"))
        return opened.select(*keys, F.col("e.at").alias("at"), *[(F.col("e.d") if s == side else F.lit(0)).alias(n) for s, n in ((0, "da"), (1, "db"))])

    order = Window.partitionBy(*keys).orderBy("at")
    so_far = order.rangeBetween(Window.unboundedPreceding, 0)
    steps = ends(a, 0).unionByName(ends(b, 1))
    if repeated:
        steps = steps.groupBy(*keys, "at").agg(F.sum("da").alias("da"), F.sum("db").alias("db"))
    marked = steps.select(*keys, F.col("at").alias("lo"), (F.lead("at").over(order) - 1).alias("hi"), (F.sum("da").over(so_far) > 0).alias("in_a"), (F.sum("db").over(so_far) > 0).alias("in_b"))
    x, y = F.col("in_a"), F.col("in_b")
    rule = {"intersect": x & y, "union": x | y, "minus": x & ~y, "symdiff": x != y}[keep]
    return coalesced(marked.filter(rule & (F.col("lo") <= F.col("hi"))).select(*keys, "lo", "hi"), keys)


def overlap_join(a: DataFrame, b: DataFrame, on: list[str], bucket: int | None = None) -> DataFrame:
    """Natural join on `on` of intervals that meet; the result has their intersection. With `bucket` (cells), both sides
    are dealt into buckets of time as well, and a pair is kept in the first bucket that it shares."""
    right = b.withColumnsRenamed({"lo": "_lo", "hi": "_hi"})
    meets = (F.col("lo") <= F.col("_hi")) & (F.col("_lo") <= F.col("hi"))
    if bucket is None:
        joined = right.withColumnsRenamed({c: f"_{c}" for c in on})
        cond = meets
        for c in on:
            cond = (F.col(c) == F.col(f"_{c}")) & cond
        joined = a.join(joined, cond).drop(*[f"_{c}" for c in on])
    else:
        dealt = lambda df, lo, hi: df.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / bucket), F.floor(F.col(hi) / bucket))))
        joined = dealt(a, "lo", "hi").join(dealt(right, "_lo", "_hi"), [*on, "_b"]).filter(meets & (F.col("_b") == F.floor(F.greatest("lo", "_lo") / bucket))).drop("_b")
    return joined.withColumn("lo", F.greatest("lo", "_lo")).withColumn("hi", F.least("hi", "_hi")).drop("_lo", "_hi")


WORD = 64


def worded(df: DataFrame, keys: list[str], bits: str) -> DataFrame:
    """The cells of each key as bits of one word for each stretch `_w` of 64 cells that it has any of."""
    cut = df.select(*keys, "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / WORD), F.floor(F.col("hi") / WORD))).alias("_w"))
    first, last = f"cast(greatest(lo - _w * {WORD}, 0) as int)", f"cast(least(hi - _w * {WORD}, {WORD - 1}) as int)"
    mask = F.expr(f"shiftleft(-1L, {first}) & shiftrightunsigned(-1L, {WORD - 1} - {last})")
    return cut.select(*keys, "_w", mask.alias(bits)).groupBy(*keys, "_w").agg(F.bit_or(bits).alias(bits))


def unworded(df: DataFrame, keys: list[str], bits: str) -> DataFrame:
    """worded backwards: the runs of bits, cut at the ends of stretches."""
    places = lambda x: F.expr(f"filter(sequence(0, {WORD - 1}), i -> getbit({x}, i) = 1)")
    ends = df.select(*keys, "_w", F.expr(f"{bits} & ~shiftleft({bits}, 1)").alias("_lo"), F.expr(f"{bits} & ~shiftrightunsigned({bits}, 1)").alias("_hi"))
    runs = ends.select(*keys, "_w", places("_lo").alias("_lo"), places("_hi").alias("_hi")).select(*keys, "_w", F.inline(F.arrays_zip("_lo", "_hi")))
    return runs.select(*keys, *[(F.col("_w") * WORD + F.col(f"_{c}")).alias(c) for c in EDGE])


def overlap_join_in_words(a: DataFrame, b: DataFrame, on: list[str], keep: list[str]) -> DataFrame:
    """The keys `keep` of overlap_join, by words of 64 cells: pairs and pieces of a result are not rows but bits of one
    row for each of its stretches. For keys that meet at very many times within not too many stretches."""
    met = worded(a, keys_of(a), "_a").join(worded(b, keys_of(b), "_b"), [*on, "_w"])
    both = met.select(*keep, "_w", F.expr("_a & _b").alias("_bits")).filter("_bits != 0")
    return unworded(both.groupBy(*keep, "_w").agg(F.bit_or("_bits").alias("_bits")), keep, "_bits")


def clipped(df: DataFrame, lo: int | None, hi: int | None) -> DataFrame:
    if lo is not None:
        df = df.filter(F.col("hi") >= lo).withColumn("lo", F.greatest("lo", F.lit(lo).cast("long")))
    if hi is not None:
        df = df.filter(F.col("lo") <= hi).withColumn("hi", F.least("hi", F.lit(hi).cast("long")))
    return df


def shifted(df: DataFrame, by_cells: int | Column) -> DataFrame:
    return df.withColumn("lo", F.col("lo") + by_cells).withColumn("hi", F.col("hi") + by_cells)


def gaps(df: DataFrame, lo: int, hi: int, least: int = 1, keys: list[str] | None = None) -> DataFrame:
    """Maximal free ranges of at least `least` cells of each key within [lo, hi]."""
    return complement(df, lo, hi, keys).filter(F.col("hi") - F.col("lo") + 1 >= least)


def complement(df: DataFrame, lo: int, hi: int, keys: list[str] | None = None) -> DataFrame:
    """What each key of df lacks within [lo, hi]."""
    keys = keys_of(df) if keys is None else keys
    whole = df.select(*keys).distinct().select(*keys, F.lit(lo).cast("long").alias("lo"), F.lit(hi).cast("long").alias("hi"))
    return sweep(whole, df.select(*keys, "lo", "hi"), "minus", keys)


def durations(df: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Number of intervals and of cells of each key."""
    keys = keys_of(df) if keys is None else keys
    return coalesced(df, keys).groupBy(*keys).agg(F.count(F.lit(1)).alias("intervals"), F.sum(F.col("hi") - F.col("lo") + 1).alias("cells"))


def packed(df: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """One row a key with its sorted intervals."""
    keys = keys_of(df) if keys is None else keys
    return df.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("lo", "hi"))).alias("set"))


def unpacked(df: DataFrame) -> DataFrame:
    return df.select(*[c for c in df.columns if c != "set"], F.inline("set"))


def at_cell(df: DataFrame, cell: int) -> DataFrame:
    return df.filter((F.col("lo") <= cell) & (F.col("hi") >= cell))


def as_of(facts: DataFrame, probes: DataFrame, keys: list[str], value: str) -> DataFrame:
    """probes (keys, at, further columns) with the value of the latest fact (keys, at, value) at or before them."""
    rest = [c for c in probes.columns if c not in (*keys, "at")]
    left = facts.select(*keys, "at", F.lit(0).alias("_probe"), F.col(value).alias("_v"), *[F.lit(None).cast(probes.schema[c].dataType).alias(c) for c in rest])
    both = left.unionByName(probes.select(*keys, "at", F.lit(1).alias("_probe"), F.lit(None).cast(facts.schema[value].dataType).alias("_v"), *rest))
    order = Window.partitionBy(*keys).orderBy("at", "_probe").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("_v", ignorenulls=True).over(order)).filter("_probe = 1").select(*keys, "at", *rest, value)


# Operators of the rule language on coalesced interval relations. `past` looks back, `next` looks ahead.


def past_some(df: DataFrame, r: Range) -> DataFrame:
    lo, hi = cells.dilated(F.col("lo"), F.col("hi"), r)
    return df.select(*keys_of(df), lo.alias("lo"), hi.alias("hi"))


def next_some(df: DataFrame, r: Range) -> DataFrame:
    lo, hi = cells.mirrored(cells.dilated, F.col("lo"), F.col("hi"), r)
    return df.select(*keys_of(df), lo.alias("lo"), hi.alias("hi"))


def past_all(df: DataFrame, r: Range) -> DataFrame:
    lo, hi = cells.eroded(F.col("lo"), F.col("hi"), r)
    return df.select(*keys_of(df), lo.alias("lo"), hi.alias("hi")).filter("lo <= hi")


def next_all(df: DataFrame, r: Range) -> DataFrame:
    lo, hi = cells.mirrored(cells.eroded, F.col("lo"), F.col("hi"), r)
    return df.select(*keys_of(df), lo.alias("lo"), hi.alias("hi")).filter("lo <= hi")


def _through(holds: DataFrame, trigger: DataFrame, r: Range, ahead: bool) -> DataFrame:
    """Since (ahead: until): triggers carried within r along the closure of a maximal holding interval."""
    on = [c for c in keys_of(holds) if c in keys_of(trigger)]
    lo, hi = cells.closure(F.col("lo"), F.col("hi"))
    closed = holds.select(*keys_of(holds), lo.alias("lo"), hi.alias("hi")).withColumn("_cl", F.col("lo")).withColumn("_ch", F.col("hi"))
    met = overlap_join(trigger, closed, on)
    moved = next_some(met, r) if ahead else past_some(met, r)
    inside = moved.withColumn("lo", F.greatest("lo", "_cl")).withColumn("hi", F.least("hi", "_ch")).drop("_cl", "_ch").filter("lo <= hi")
    if r.has_zero:
        extra = [c for c in keys_of(holds) if c not in on]
        if extra:  # a trigger counts at once for every holder of its keys
            here = trigger.join(holds.select(*keys_of(holds)).distinct(), on) if on else trigger.crossJoin(holds.select(*extra).distinct())
            inside = inside.unionByName(here.select(*inside.columns))
        else:
            inside = inside.unionByName(trigger.select(*inside.columns))
    return inside


def since(holds: DataFrame, trigger: DataFrame, r: Range) -> DataFrame:
    return _through(holds, trigger, r, ahead=False)


def until(holds: DataFrame, trigger: DataFrame, r: Range) -> DataFrame:
    return _through(holds, trigger, r, ahead=True)
