"""Toxicity scores learned from confirmed toxic texts and unlabelled text.

Features are the presence of hashed words and of hashed word beginnings. A logistic model is fitted in numpy on the
non-negative positive-unlabelled risk: prior * loss(positives as 1) + max(0, loss(unlabelled as 0) - prior *
loss(positives as 0)); when the second part falls below zero its gradient is reversed.

Edge cases: null texts count as empty; empty texts get the score of the model's constant alone; repeated rows get
equal scores; without a positive example every score is 0; further columns are ignored.
The fit uses at most about `POSITIVES` confirmed and `UNLABELLED` other documents (chosen by a hash of their id).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textscan as ts

POSITIVES = 4000
UNLABELLED = 8000
BITS = 20
BEGINNINGS = (3, 4, 5, 6, 7)
SELECTED = 3000


def _features(words: ts.Words) -> tuple[np.ndarray, np.ndarray]:
    """(document, bucket) of each word and beginning."""
    owner = words.owner()
    docs, buckets = [owner], [words.hashes >> np.uint64(64 - BITS)]
    for n in BEGINNINGS:
        h, at = words.prefixes(n)
        docs.append(owner[at])
        buckets.append(h >> np.uint64(64 - BITS))
    return np.concatenate(docs), np.concatenate(buckets).astype(np.int64)


def _bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        kind = batch.column("positive")
        for a, b, data, offsets in ts.slices(batch.column("text")):
            docs, buckets = _features(ts.scan(data, offsets, ts.PLAIN))
            pairs = np.unique(docs.astype(np.int64) << BITS | buckets)
            owner = pairs >> BITS
            lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(owner, np.arange(b - a + 1)), pa.int32()), pa.array((pairs & ((1 << BITS) - 1)).astype(np.int32)))
            yield pa.RecordBatch.from_arrays([kind.slice(a, b - a), lists], ["positive", "bag"])


@dataclass
class Model:
    weights: np.ndarray
    constant: float
    prior: float

    def score(self, words: ts.Words) -> np.ndarray:
        docs, buckets = _features(words)
        hit = self.weights[buckets] != 0
        pairs = np.unique(docs[hit].astype(np.int64) << BITS | buckets[hit])
        z = np.bincount(pairs >> BITS, weights=self.weights[pairs & ((1 << BITS) - 1)], minlength=len(words.first) - 1)
        return 1 / (1 + np.exp(-np.clip(z + self.constant, -30, 30)))


def fit_risk(bags: list[np.ndarray], positive: np.ndarray, prior: float, selected: int = SELECTED, steps: int = 400, rate: float = 0.05, ridge: float = 2e-4) -> Model:
    """Minimise the corrected risk on features that are commoner in positives."""
    size = 1 << BITS
    sizes = np.fromiter(map(len, bags), np.int64, len(bags))
    flat = np.concatenate([np.zeros(0, np.int32), *bags])
    owner = np.repeat(np.arange(len(bags)), sizes)
    n_p, n_u = int(positive.sum()), int((~positive).sum())
    weights = np.zeros(size)
    if not n_p or not n_u:
        return Model(weights, -30.0, prior)
    in_p = np.bincount(flat[positive[owner]], minlength=size)
    in_u = np.bincount(flat[~positive[owner]], minlength=size)
    p, u = (in_p + 0.5) / (n_p + 1), (in_u + 0.5) / (n_u + 1)
    z = np.where(in_p >= max(4, n_p // 500), (p - u) / np.sqrt(p * (1 - p) / n_p + u * (1 - u) / n_u), -np.inf)
    chosen = np.argsort(-z, kind="stable")[:selected]
    chosen = chosen[z[chosen] > 4]
    column = np.full(size, -1)
    column[chosen] = np.arange(len(chosen))
    keep = column[flat] >= 0
    col, row = column[flat[keep]], owner[keep]
    w, c = np.zeros(len(chosen) + 1), np.log(prior / (1 - prior))
    w[-1] = c
    m, v = np.zeros_like(w), np.zeros_like(w)
    for step in range(1, steps + 1):
        f = np.bincount(row, weights=w[col], minlength=len(bags)) + w[-1]
        s = 1 / (1 + np.exp(-np.clip(f, -30, 30)))
        loss0 = np.logaddexp(0, f)
        rest = loss0[~positive].mean() - prior * loss0[positive].mean()
        # Slope of each document's part of the risk.
        g_rest = np.where(positive, -prior * s / n_p, s / n_u)
        g = np.where(positive, -prior * (1 - s) / n_p, 0.0) + g_rest if rest >= 0 else -g_rest
        grad = np.append(np.bincount(col, weights=g[row], minlength=len(chosen)) + ridge * w[:-1], g.sum())
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        w -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    weights[chosen] = w[:-1]
    return Model(weights, float(w[-1]), prior)


def learn(docs: DataFrame, labels: DataFrame, may_learn: Column, positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> Model:
    """Fit from labels.toxic = 1 and unlabelled text; may_learn: a condition on doc_id that both must meet."""
    known = labels.select("doc_id", "toxic").filter(may_learn & F.col("doc_id").isNotNull() & F.col("toxic").isNotNull())
    n_all, n_toxic = known.agg(F.count(F.lit(1)), F.count_if(F.col("toxic") == 1)).first()
    if not n_toxic:
        return fit_risk([], np.zeros(0, bool), 0.5)
    prior = min(0.95, max(0.001, n_toxic / n_all))
    ids = known.filter("toxic = 1").select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(positives)
    text = docs.select("doc_id", "text").filter(may_learn & F.col("text").isNotNull())
    share = unlabelled / max(1, docs.count())
    sampled = text.filter(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1 << 30)) < share * float(1 << 30)).withColumn("positive", F.lit(False))
    # At most `positives` ids are broadcast.
    chosen = text.join(F.broadcast(ids), "doc_id", "left_semi").withColumn("positive", F.lit(True))
    got = chosen.unionByName(sampled).select("positive", "text").transform(ts.mapped, _bags, "positive boolean, bag array<int>").toArrow()
    bag = got.column("bag").combine_chunks()
    bag = pa.concat_arrays(bag.chunks) if isinstance(bag, pa.ChunkedArray) else bag
    offsets, flat = bag.offsets.to_numpy(), bag.values.to_numpy()
    bags = [flat[a:b] for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
    return fit_risk(bags, got.column("positive").to_numpy(), prior)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and score of every whole text."""
    w = docs.sparkSession.sparkContext.broadcast((model.weights.astype(np.float32), model.constant, model.prior))  # 2**BITS floats

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Model(*w.value)
        for batch in batches:
            parts = [m.score(ts.scan(data, offsets, ts.PLAIN)) for _, _, data, offsets in ts.slices(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.concatenate([np.zeros(0), *parts]))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).transform(ts.mapped, run, "doc_id long, score double")
