"""Quality selection by importance resampling.

Two generative models of hashed word n-grams (orders 1 and 2, one table of buckets) are fitted: one on target text,
one on the raw text of all documents. A document's log weight is the log ratio of its probabilities under the two;
documents are sampled without replacement by Gumbel top-k: the k largest sums of log weight and a keyed Gumbel number.

k may be given. By default it is the number of documents whose log weight reaches the cut that best divides a labelled
sample into target and other text, so that the draw takes as much as the target supports.

Edge cases: null texts count as empty; empty texts have weight 0; equal keys at the edge of the draw are all taken;
repeated rows have equal keys; without a labelled target row all documents stay; all columns pass unchanged.
The target model and the cut use at most about `LABELLED` labelled documents of each class; raw counts use all texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts

BUCKETS = 10_000
LABELLED = 10_000
SMOOTHING = 0.5
#: Raw-model counts added to the target's, for each bucket on average.
LEANING = 20.0
SEED = 20_240_101


def ngrams(words: ts.Words, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """(document, bucket) of all words and adjacent pairs of words."""
    owner = words.owner()
    h = words.hashes
    pair = owner[1:] == owner[:-1] if len(owner) else np.zeros(0, bool)
    with np.errstate(over="ignore"):
        two = ts.mix(h[:-1] * np.uint64(ts.BASE) + h[1:])[pair] if len(h) else h
    return np.concatenate([owner, owner[1:][pair] if len(owner) else owner]), (np.concatenate([h, two]) % np.uint64(buckets)).astype(np.int64)


def bucket_counts(df: DataFrame, buckets: int = BUCKETS) -> np.ndarray:
    """n-gram counts of all texts; each task sends one row for each bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(buckets, np.int64)
        for batch in batches:
            for _, _, data, offsets in ts.slices(batch.column("text")):
                total += np.bincount(ngrams(ts.scan(data, offsets), buckets)[1], minlength=buckets)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["bucket", "n"])

    counted = df.select(F.col("text").cast("string").alias("text")).transform(ts.mapped, run, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    out = np.zeros(buckets, np.int64)
    for b, n in counted.collect():  # at most `buckets` rows
        out[b] = n
    return out


@dataclass
class Weigher:
    """Log ratios by bucket."""

    ratio: np.ndarray

    @classmethod
    def fitted(cls, target: np.ndarray, raw: np.ndarray) -> Weigher:
        q = (raw + SMOOTHING) / (raw.sum() + SMOOTHING * len(raw))
        # The target model leans on the raw one where it has seen little, so rare n-grams weigh little.
        p = (target + LEANING * len(raw) * q) / (target.sum() + LEANING * len(raw))
        return cls(np.log(p / q))

    def weigh(self, column: pa.Array) -> np.ndarray:
        parts = [np.zeros(0)]
        for a, b, data, offsets in ts.slices(column):
            docs, buckets = ngrams(ts.scan(data, offsets), len(self.ratio))
            parts.append(np.bincount(docs, weights=self.ratio[buckets], minlength=b - a))
        return np.concatenate(parts)


def gumbel(ids: pa.Array, seed: int = SEED) -> np.ndarray:
    """A Gumbel number for each id, the same in every run."""
    x = ids.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
    with np.errstate(over="ignore"):
        u = (ts.mix(x + np.uint64(seed) * np.uint64(ts.BASE)) >> np.uint64(11)).astype(float)
    return -np.log(-np.log((u + 0.5) / 2**53))


def weighed(df: DataFrame, weigher: Weigher) -> DataFrame:
    """doc_id, log_weight, sample_key of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            w = weigher.weigh(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(w), pa.array(w + gumbel(batch.column("doc_id")))], ["doc_id", "log_weight", "sample_key"])

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).transform(ts.mapped, run, "doc_id long, log_weight double, sample_key double")


def labelled(docs: DataFrame, labels: DataFrame, bound: int = LABELLED) -> DataFrame:
    """doc_id, text, quality of a sample of labelled documents, at most `bound` of each class by a hash of the id."""
    known = labels.select("doc_id", "quality").filter("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    pick = lambda q: known.filter(F.col("quality") == q).orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    # At most 2 * bound rows are broadcast.
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(pick(1).unionByName(pick(0))), "doc_id")


def fit(docs: DataFrame, labels: DataFrame) -> tuple[Weigher, float] | None:
    """The weigher and the cut on log weights; None without labelled target text."""
    half = F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(2)).cast("int")
    sample = ts.stored(labelled(docs, labels).withColumn("half", half), "labelled")
    parts = [bucket_counts(sample.filter((F.col("quality") == 1) & (F.col("half") == h))) for h in (0, 1)]
    if not (parts[0] + parts[1]).sum():
        return None
    raw = bucket_counts(docs)
    # The cut is found on weights that each half gets from the other half's target model.
    known = F.broadcast(sample.select("doc_id", "quality").distinct())
    got = [weighed(sample.filter(F.col("half") == h), Weigher.fitted(parts[1 - h], raw)).join(known, "doc_id").select("log_weight", "quality").toPandas() for h in (0, 1)]
    weights, quality = (np.concatenate([g[c].to_numpy() for g in got]) for c in ("log_weight", "quality"))
    return Weigher.fitted(parts[0] + parts[1], raw), best_cut(weights, quality == 1)


def best_cut(weights: np.ndarray, is_target: np.ndarray) -> float:
    """The middle between neighbouring weights at which target and other text are divided best; -inf if all are target."""
    if is_target.all() or not is_target.any():
        return -np.inf
    order = np.argsort(weights, kind="stable")
    w, t = weights[order], is_target[order]
    lost = np.concatenate([[0], np.cumsum(t)]) / t.sum()
    caught = np.concatenate([[0], np.cumsum(~t)]) / (~t).sum()
    gain = caught - 4 * lost  # losing target text weighs more
    i = int(gain.argmax())
    if i == 0:
        return -np.inf
    return float(w[-1] + 1) if i == len(w) else float((w[i - 1] + w[i]) / 2)


def kth_largest(df: DataFrame, column: str, k: int) -> float:
    """The k-th largest value, by counting in ever narrower bins; the driver gets at most `bins` rows a pass."""
    bins, need = 4096, k
    low, high = df.agg(F.min(column), F.max(column)).first()
    x = F.col(column)
    while low < high:
        width = (high - low) / bins
        if width <= 0 or low + width == low:
            break
        spot = F.least(F.floor((x - low) / width), F.lit(bins - 1)).cast("int")
        rows = df.filter((x >= low) & (x <= high)).groupBy(spot.alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min(column).alias("lo"), F.max(column).alias("hi")).collect()
        for r in sorted(rows, reverse=True):
            if need <= r["n"]:
                low, high = r["lo"], r["hi"]
                break
            need -= r["n"]
    return low


@dataclass
class Draw:
    weigher: Weigher
    k: int
    threshold: float


def plan_draw(docs: DataFrame, labels: DataFrame, k: int | None = None) -> Draw | None:
    """Fit, and find the key of the k-th document of the Gumbel order over all documents."""
    fitted = fit(docs, labels)
    if fitted is None:
        return None
    weigher, cut = fitted
    keys = ts.stored(weighed(docs, weigher).select("log_weight", "sample_key"), "keys")
    k = keys.filter(F.col("log_weight") >= cut).count() if k is None else k
    if k <= 0:
        return Draw(weigher, 0, np.inf)
    return Draw(weigher, k, kth_largest(keys, "sample_key", min(k, keys.count())))


def resample(docs: DataFrame, labels: DataFrame, k: int | None = None) -> DataFrame:
    """The documents drawn, with all their columns."""
    draw = plan_draw(docs, labels, k)
    if draw is None:
        return docs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key = draw.weigher.weigh(batch.column("text")) + gumbel(batch.column("doc_id"))
            yield batch.filter(pa.array(key >= draw.threshold))

    return docs.transform(ts.mapped, run, docs.schema)


def judged(docs: DataFrame, labels: DataFrame, k: int | None = None) -> DataFrame:
    """doc_id, log_weight, sample_key and kept of every document."""
    draw = plan_draw(docs, labels, k)
    if draw is None:
        return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lit(0.0).alias("log_weight"), F.lit(0.0).alias("sample_key"), F.lit(True).alias("kept"))
    return weighed(docs, draw.weigher).withColumn("kept", F.col("sample_key") >= F.lit(draw.threshold))
