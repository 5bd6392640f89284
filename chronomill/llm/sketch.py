"""Threshold-scaled document sketches.

A sketch holds every 5-word shingle hash below a fixed fraction of the hash range, and no other. Sketches of parts merge
by union; containment and likeness of two texts are estimated from sketches alone, however unequal their lengths. A
sketch is written as base64 of sorted 32-bit values.

A short text may have no hash below the fraction. It is then written as `=` and its smallest hash, which stands apart
from sketches: two such texts are alike (1) if these are equal and not (0) otherwise, and unlike any with a sketch.

Edge cases: null texts count as empty; empty texts have an empty fingerprint, which is like another empty one (1) and
unlike any other (0); texts with 1 to 4 words have one shingle; null ids sort first; rows with equal ids are ordered
by text; further columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts

FRACTION = 0.25
WORDS = 5
LEAST_ID = -(1 << 63)


def fingerprints(texts: pa.Array, fraction: float = FRACTION, k: int = WORDS) -> list[tuple[np.ndarray, int | None]]:
    """Sorted 32-bit sketch values of each text, and the smallest hash of a text with shingles but none of these."""
    limit = np.uint64(int(fraction * 2**64) - 1 if fraction < 1 else 2**64 - 1)
    shift = np.uint64(32 - int(-math.log2(fraction))) if fraction < 1 else np.uint64(32)
    out: list[tuple[np.ndarray, int | None]] = []
    for _, _, data, offsets in ts.slices(texts):
        h, first = ts.shingles(ts.scan(data, offsets), k)
        kept = h <= limit
        low, at = h[kept], np.concatenate([[0], np.cumsum(kept)])
        for a, b in zip(first[:-1], first[1:], strict=True):
            part = low[at[a] : at[b]]
            out.append((np.unique((part >> shift).astype(np.uint32)), int(h[a:b].min()) if b > a and not len(part) else None))
    return out


def sketches(texts: pa.Array, fraction: float = FRACTION, k: int = WORDS) -> list[np.ndarray]:
    """Sorted 32-bit sketch values of each text."""
    return [s for s, _ in fingerprints(texts, fraction, k)]


def alike(a: tuple[np.ndarray, int | None], b: tuple[np.ndarray, int | None]) -> float:
    """Estimated likeness of two fingerprints."""
    return likeness(a[0], b[0]) if len(a[0]) or len(b[0]) else float(a[1] == b[1])


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated share of common shingles among all of both."""
    if not len(a) and not len(b):
        return 1.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def containment(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated share of a's shingles that b has."""
    return 1.0 if not len(a) else len(np.intersect1d(a, b, assume_unique=True)) / len(a)


def merged(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.union1d(a, b)


def written(a: np.ndarray, least: int | None = None) -> str:
    return base64.b64encode(a.astype("<u4").tobytes()).decode() if least is None else f"={least:016x}"


def read(s: str) -> np.ndarray:
    """The sketch of a fingerprint."""
    return np.frombuffer(b"" if s.startswith("=") else base64.b64decode(s), "<u4")


def fingerprint(df: DataFrame, fraction: float = FRACTION) -> DataFrame:
    """doc_id and fingerprint of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([written(*s) for s in fingerprints(batch.column("text"), fraction)], pa.string())], ["doc_id", "fingerprint"])

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).transform(ts.mapped, run, "doc_id long, fingerprint string")


def chained(df: DataFrame, runs_per_partition: int = 4) -> DataFrame:
    """run, tail, doc_id, text in partitions sorted by these: ids fall into runs by range, and each run ends with a
    copy (tail = true) of the first row of the next one; the last run ends with the first row of all."""
    rows = df.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST_ID)).alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ids = rows.select("doc_id")
    runs = ids.repartitionByRange(max(1, parts * runs_per_partition), "doc_id").groupBy(F.spark_partition_id().alias("p")).agg(F.min("doc_id").alias("b"))
    bounds = sorted(r["b"] for r in runs.select("b").distinct().collect())  # one id for each run
    if not bounds:
        bounds = [LEAST_ID]
    n, g = len(bounds), max(1, math.isqrt(len(bounds)))
    groups = [bounds[i : i + g] for i in range(0, n, g)]
    longs = lambda xs: F.array(*[F.lit(x).cast("long") for x in xs])
    # The run of an id by two short lists of bounds, about the square root of their number each.
    up_to = lambda a: F.size(F.filter(a, lambda b: b <= F.col("doc_id")))
    group = F.greatest(up_to(longs(x[0] for x in groups)), F.lit(1)) - 1
    own = F.get(F.array(*map(longs, groups)), F.col("_g"))
    placed = rows.withColumn("_g", group).withColumn("_i", F.greatest(up_to(own), F.lit(1)) - 1)
    placed = placed.withColumn("_run", F.col("_g") * g + F.col("_i")).withColumn("_opens", F.get(own, F.col("_i")) == F.col("doc_id"))
    stays = F.struct(F.col("_run").alias("run"), F.lit(False).alias("tail"))
    ends = F.struct(F.pmod(F.col("_run") - 1, F.lit(n)).alias("run"), F.lit(True).alias("tail"))
    both = placed.select(F.explode(F.when(F.col("_opens"), F.array(stays, ends)).otherwise(F.array(stays))).alias("at"), "doc_id", "text")
    return both.select("at.run", "at.tail", "doc_id", "text").repartition(parts, "run").sortWithinPartitions("run", "tail", "doc_id", "text")


CHAIN_SCHEMA = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _compare(rows: list[tuple[int, bool, int, str]], fraction: float) -> pa.RecordBatch:
    """Rows (run, tail, id, text) in order; each but the last one of a run is compared with its follower."""
    pairs = [(x, y) for x, y in zip(rows[:-1], rows[1:], strict=True) if not x[1]]
    texts = [x[3] for x, _ in pairs]
    edited = []
    for x, y in pairs:
        cut = len(x[3]) // 4
        edited.append(x[3][: len(x[3]) - cut] + y[3][:cut])
    own = fingerprints(pa.array([r[3] for r in rows], pa.large_string()), fraction)
    ahead = {i: own[i + 1] for i in range(len(rows) - 1) if not rows[i][1]}
    mine = [own[i] for i in ahead]
    changed = fingerprints(pa.array(edited, pa.large_string()), fraction)
    return pa.RecordBatch.from_pydict({
        "doc_id": pa.array([None if x[2] == LEAST_ID else x[2] for x, _ in pairs], pa.int64()),
        "n_chars": pa.array(map(len, texts), pa.int64()),
        "edited_sha256": pa.array([hashlib.sha256(e.encode()).hexdigest() for e in edited], pa.string()),
        "fingerprint": pa.array([written(*m) for m in mine], pa.string()),
        "edited_fingerprint": pa.array([written(*c) for c in changed], pa.string()),
        "near_edited": pa.array([alike(a, b) for a, b in zip(mine, changed, strict=True)], pa.float64()),
        "near_next": pa.array([alike(a, b) for a, b in zip(mine, ahead.values(), strict=True)], pa.float64()),
    })


def compare_with_next(df: DataFrame, fraction: float = FRACTION) -> DataFrame:
    """Each document's fingerprint, that of its text with the last quarter replaced by the next document's beginning,
    and the likeness of its fingerprint to that one and to the next document's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, bool, int, str]] = []
        size = 0
        for batch in batches:
            for at in range(0, len(batch), 64):
                part = batch.slice(at, 64)
                for row in zip(*(part.column(c).to_pylist() for c in ("run", "tail", "doc_id", "text")), strict=True):
                    if held and held[-1][1] and held[-1][0] == row[0]:
                        continue  # a run needs the first tail row only
                    held.append(row)
                    size += len(row[3])
                if size > ts.SLICE_BYTES:
                    yield _compare(held, fraction)
                    held, size = held[-1:], len(held[-1][3])
        if len(held) > 1:
            yield _compare(held, fraction)

    return chained(df).transform(ts.mapped, run, CHAIN_SCHEMA)
