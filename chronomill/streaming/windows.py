"""Window formulations of non-recursive rules; they serve batch frames and streams alike."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _timed(events: DataFrame) -> DataFrame:
    return events.select(F.col("user_id").alias("u"), F.col("event_type").alias("c"), "value", F.col("ts").cast("timestamp").alias("ts"))


def tumbling_counts(events: DataFrame, width: str, late: str = "1 day") -> DataFrame:
    df = _timed(events)
    df = df.withWatermark("ts", late) if df.isStreaming else df
    return df.groupBy(F.window("ts", width).alias("w"), "c").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select("c", F.col("w.start").alias("start"), "n", "total")


def sliding_counts(events: DataFrame, width: str, step: str, late: str = "1 day") -> DataFrame:
    """`some instant of the last width` as a sliding count."""
    df = _timed(events)
    df = df.withWatermark("ts", late) if df.isStreaming else df
    return df.groupBy(F.window("ts", width, step).alias("w"), "c").agg(F.count(F.lit(1)).alias("n")).select("c", F.col("w.start").alias("start"), "n")


def session_spans(events: DataFrame, gap: str, late: str = "1 day") -> DataFrame:
    """Coalesced activity of each user: sessions with a gap."""
    df = _timed(events)
    df = df.withWatermark("ts", late) if df.isStreaming else df
    return df.groupBy(F.session_window("ts", gap).alias("w"), "u").agg(F.count(F.lit(1)).alias("n")).select("u", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    df = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if df.isStreaming else df.dropDuplicates(["event_id"])


def paired(left: DataFrame, right: DataFrame, within: str, late: str = "1 day") -> DataFrame:
    """Events of two streams of a user at most `within` apart: a two-atom body without recursion."""
    a = _timed(left).select("u", F.col("c").alias("c1"), F.col("ts").alias("t1"))
    b = _timed(right).select(F.col("u").alias("u2"), F.col("c").alias("c2"), F.col("ts").alias("t2"))
    if a.isStreaming:
        a, b = a.withWatermark("t1", late), b.withWatermark("t2", late)
    return a.join(b, F.expr(f"u = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("u", "c1", "c2", "t1", "t2")
