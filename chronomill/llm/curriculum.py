"""Mixing sources to target weights along a time-varying curriculum (DataFrame functions only).

Sources get a share of the words to train on by weight, at most a number of times their size; what exceeds that is
shared again (in closed form: sources sorted by size over weight fill up first). Each source has a schedule: a
piecewise linear weight over training time 0 to 1, whose integral is scaled to the source's target. Its documents,
in an order fixed by a hash, are read again and again until the target is used up; the words read before a document
are looked up in the inverse of the integrated schedule, which gives its training position. Ranges of positions are
then sorted.

Edge cases: null texts have size 0 and are never taken; a null source is a source of its own, last in order; repeated
rows are documents of their own; an empty table gives no rows; all columns pass (the table is not asked for more than
doc_id, text and source; names with a leading _mix_ are used inside).
Running sums are taken within hash buckets of about `BUCKET_ROWS` rows, over the buckets of a block of `BLOCK_BUCKETS`,
and over the blocks of a source, so a source of any size is spread over tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import textscan as ts

WEIGHTS = (5, 2, 1)
TOTAL = 1.5
MOST = 2
BUCKET_ROWS = 200
BLOCK_BUCKETS = 1000
#: Knots (time, weight) of the schedule of each weight class: heavy sources fade, light ones grow.
SCHEDULES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)))


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, total: float = TOTAL, most: int = MOST) -> DataFrame:
    """source, source_size, weight_class, target of a table (source, size). One row a source is ordered in one task."""
    by = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    at = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    ranked = by.withColumn("weight_class", at).withColumn("w", F.element_at(F.array(*map(F.lit, weights)), F.col("weight_class") + 1))
    # Level: words for one unit of weight. The sources that fill up come first by size over weight.
    order = Window.orderBy(F.col("source_size") / F.col("w"), F.col("source").asc_nulls_last())
    full_before = F.coalesce(F.sum(most * F.col("source_size")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    weight_left = F.sum("w").over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    everything = F.sum("source_size").over(Window.partitionBy())
    level = (total * everything - full_before) / weight_left
    levels = ranked.withColumn("level", level).withColumn("open", F.col("level") * F.col("w") < most * F.col("source_size"))
    first = F.first(F.when(F.col("open"), F.col("level")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    target = F.least((most * F.col("source_size")).cast("double"), F.coalesce(F.col("w") * first, F.lit(float("inf"))))
    return levels.withColumn("target", target).select("source", "source_size", "weight_class", "target")


def position(share: Column, knots: tuple[tuple[float, float], ...]) -> Column:
    """The time by which a schedule has asked for the given share (0 to 1) of its whole demand."""
    areas = [(b[0] - a[0]) * (a[1] + b[1]) / 2 for a, b in zip(knots[:-1], knots[1:], strict=True)]
    out: Column = F.lit(knots[-1][0])
    before = sum(areas)
    for (t0, w0), (t1, w1), area in reversed([*zip(knots[:-1], knots[1:], areas, strict=True)]):
        before -= area
        u = F.greatest(share * sum(areas) - before, F.lit(0.0))
        slope = (w1 - w0) / (t1 - t0)
        # Root of w0 * x + slope * x^2 / 2 = u, in the form that is stable for a small slope.
        root = 2 * u / (w0 + F.sqrt(F.greatest(w0 * w0 + 2 * slope * u, F.lit(0.0))))
        out = F.when(share * sum(areas) < before + area, F.coalesce(root + t0, F.lit(t0))).otherwise(out)
    return out


def planned(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, total: float = TOTAL, most: int = MOST, carry: bool = False) -> DataFrame:
    """doc_id, source, size, source_size, weight_class, target, offset (the source's words before the document in its
    order) of every document; with carry also its whole row, as _mix_row."""
    size = ts.word_count(F.col("text"))
    key = F.xxhash64("doc_id", F.xxhash64("text"))
    rows = docs.select("doc_id", "source", size.alias("size"), key.alias("_mix_key"), *([F.struct(*docs.columns).alias("_mix_row")] if carry else []))
    small = ts.stored(rows.select("source", "size", "_mix_key"), "sizes")
    buckets = max(16, small.count() // BUCKET_ROWS)
    bucket = F.pmod(F.shiftrightunsigned("_mix_key", 8), F.lit(buckets)).cast("int")
    goals = targets(small.select("source", "size"), weights, total, most)
    up_to = lambda w: F.coalesce(F.sum("_mix_sum").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    block = F.floor(F.col("_mix_b") / BLOCK_BUCKETS)
    sums = small.groupBy(F.col("source").alias("_mix_source"), bucket.alias("_mix_b")).agg(F.sum("size").alias("_mix_sum")).withColumn("_mix_block", block)
    blocks = sums.groupBy("_mix_source", "_mix_block").agg(F.sum("_mix_sum").alias("_mix_sum"))
    blocks = blocks.select(F.col("_mix_source").alias("_mix_s"), F.col("_mix_block").alias("_mix_k"), up_to(Window.partitionBy("_mix_source").orderBy("_mix_block")).alias("_mix_before"))
    starts = sums.withColumn("_mix_own", up_to(Window.partitionBy("_mix_source", "_mix_block").orderBy("_mix_b")))
    starts = starts.join(blocks, F.col("_mix_source").eqNullSafe(F.col("_mix_s")) & (F.col("_mix_block") == F.col("_mix_k")))
    starts = starts.select("_mix_source", "_mix_b", (F.col("_mix_before") + F.col("_mix_own")).alias("_mix_start"))
    goals = goals.withColumnRenamed("source", "_mix_goal")
    offsets = ts.stored(starts.join(goals, F.col("_mix_source").eqNullSafe(F.col("_mix_goal"))).drop("_mix_goal"), "offsets")
    placed = rows.withColumn("_mix_bucket", bucket)
    if not carry:
        placed = placed.repartition("source", "_mix_bucket")
    joined = placed.join(offsets, F.col("source").eqNullSafe(F.col("_mix_source")) & (F.col("_mix_bucket") == F.col("_mix_b")))
    within = Window.partitionBy("source", "_mix_bucket").orderBy("_mix_key", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    return joined.withColumn("offset", F.col("_mix_start") + F.coalesce(F.sum("size").over(within), F.lit(0))).drop("_mix_bucket", "_mix_b", "_mix_source", "_mix_start", "_mix_key")


def reads(most: int, whole: bool) -> Column:
    """The reads of a planned document that begin within its source's target: words, and the training position at which
    the integrated schedule asks for the first of them. whole: all words of a read, if at least half lie within the target."""
    def read(epoch: Column) -> Column:
        at = F.col("offset") + epoch * F.col("source_size")
        left = F.floor("target") - at
        words = F.when(at + F.col("size") / 2 <= F.col("target"), F.col("size")).otherwise(F.lit(0)) if whole else F.least(F.greatest(left, F.lit(0)), F.col("size"))
        return F.struct(words.cast("long").alias("words"), _scheduled(at).alias("position"))

    return F.filter(F.transform(F.sequence(F.lit(0), F.lit(most - 1)), read), lambda r: r["words"] > 0)


def _in_order(df: DataFrame, position: str) -> DataFrame:
    """df range-sorted by training position (nulls last), then id."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = [F.col(position).asc_nulls_last(), F.col("doc_id")]
    return df.repartitionByRange(parts, *order).sortWithinPartitions(*order)


def mix(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken, first_position, positions (of all its reads) of every document, in
    training order: taken are the words of its reads; the last document of a source may be taken in part, so that a
    source's taken words are its target rounded down. Documents without a read come last."""
    plan = planned(docs, **options).withColumn("_mix_reads", reads(options.get("most", MOST), whole=False))
    taken = F.aggregate("_mix_reads", F.lit(0).cast("long"), lambda n, r: n + r["words"])
    positions = F.transform("_mix_reads", lambda r: r["position"])
    return _in_order(plan.select("doc_id", "size", "source_size", "target", taken.alias("taken"), F.get(positions, F.lit(0)).alias("first_position"), positions.alias("positions")), "first_position")


def _scheduled(words: Column) -> Column:
    share = F.least(F.coalesce(F.try_divide(words, "target"), F.lit(0.0)), F.lit(1.0))
    out = position(share, SCHEDULES[0])
    for i, knots in enumerate(SCHEDULES[1:], 1):
        out = F.when(F.col("weight_class") % len(SCHEDULES) == i, position(share, knots)).otherwise(out)
    return out


def curriculum(docs: DataFrame, **options) -> DataFrame:
    """The documents in training order with all their columns, a copy for each time that they are read; the last
    document of a source is read if at least half of it is within the target."""
    plan = planned(docs, carry=True, **options).select(F.explode(reads(options.get("most", MOST), whole=True)["position"]).alias("_mix_position"), "doc_id", "_mix_row")
    return _in_order(plan, "_mix_position").select("_mix_row.*")
