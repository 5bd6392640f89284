"""Exact top-k inner-product search over quantised vectors with MaxScore pruning.

A dimension is a term: its posting list in a shard holds one impact for each row. The query's contribution in a
dimension lies between two bounds taken from the shard; dimensions with small bounds are non-essential as long as
their bounds together cannot lift a row over the running k-th score. Essential lists are traversed for all rows,
the others are probed for rows that stay competitive. Rows are dealt into shards and queries into blocks of fixed
size, each pair of which is one group; shard results are merged by rank.

Edge cases: null vectors and vectors with null or non-finite components take no part; shorter vectors count zeros
for missing components; an id's own rows are never its candidates; equal scores go to the smaller id; fewer
candidates than k give fewer rows; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SHARD_ROWS = 2048
BLOCK_QUERIES = 1024
SCALE = 256


def quantised(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = SCALE) -> DataFrame:
    """(id, vec array<long>): floor(scale * x) of rows whose components are all finite numbers."""
    v = F.col(vec_col)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < float("inf")))
    return df.filter(v.isNotNull() & F.col(id_col).isNotNull() & fine).select(F.col(id_col).cast("long").alias("id"), F.transform(v, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")).cast("long")).alias("vec"))


def top_k(df: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = SCALE, shard_rows: int = SHARD_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """query_id, rank, vec_id, score: the k best candidates of each query row (is_query: a condition on column id)."""
    rows = quantised(df, id_col, vec_col, scale)
    n, q = rows.agg(F.count(F.lit(1)), F.count_if(is_query)).first()
    shards, blocks = max(1, -(-n // shard_rows)), max(1, -(-q // block_queries))
    key = F.xxhash64("id")
    every = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    lists = rows.select(F.pmod(key, F.lit(shards)).cast("int").alias("shard"), every(blocks).alias("block"), F.lit(False).alias("asks"), "id", "vec")
    asked = rows.filter(is_query).select(every(shards).alias("shard"), F.pmod(F.shiftrightunsigned(key, 20), F.lit(blocks)).cast("int").alias("block"), F.lit(True).alias("asks"), "id", "vec")
    found = lists.unionByName(asked).groupBy("shard", "block").applyInArrow(lambda t: _search(t, k), "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _matrix(t: pa.Table, width: int) -> np.ndarray:
    column = t.column("vec").combine_chunks()
    column = column if isinstance(column, pa.ListArray) else pa.concat_arrays(column.chunks)
    sizes = np.diff(column.offsets.to_numpy())
    out = np.zeros((len(sizes), width), np.int64)
    at = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    out[np.repeat(np.arange(len(sizes)), sizes), at] = column.flatten().to_numpy()
    return out


def _search(t: pa.Table, k: int) -> pa.Table:
    asks = t.column("asks").to_numpy(zero_copy_only=False)
    queries, rows = t.filter(pa.array(asks)), t.filter(pa.array(~asks))
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    if len(queries) and len(rows):
        import pyarrow.compute as pc

        width = max(1, pc.max(pc.list_value_length(t.column("vec"))).as_py())
        shard = Shard(rows.column("id").to_numpy(), _matrix(rows, width))
        for query_id, vec in zip(queries.column("id").to_numpy(), _matrix(queries, width), strict=True):
            ids, scores = shard.best(vec, k, int(query_id))
            out.append((np.full(len(ids), query_id), ids, scores))
    cat = lambda i: np.concatenate([np.zeros(0, np.int64), *(x[i] for x in out)]).astype(np.int64)
    return pa.table({"query_id": cat(0), "vec_id": cat(1), "score": cat(2)})


class Shard:
    """Posting lists of some rows, one for each dimension, with their bounds."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        order = np.argsort(ids, kind="stable")
        self.ids = ids[order]
        self.lists = np.ascontiguousarray(vectors[order].T)
        self.low, self.high = self.lists.min(1), self.lists.max(1)
        peak = np.abs(self.lists).max(1).astype(float)
        self.peak = peak
        self.real = self.lists.astype(np.float64)

    def best(self, query: np.ndarray, k: int, own: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and exact scores of the k best rows, ties to the smaller id."""
        exact = float(np.abs(query) @ self.peak) < 2.0**52  # float sums of integers are exact then
        q, lists = (query.astype(np.float64), self.real) if exact else (query, self.lists)
        a, b = query * self.low, query * self.high
        least, bound = np.minimum(a, b), np.abs(b - a)
        order = np.argsort(-bound, kind="stable")
        rest = np.concatenate([np.cumsum(bound[order][::-1])[::-1], [0]])
        floor = int(least.sum())
        open_rows = np.flatnonzero(self.ids != own)
        if len(open_rows) > k:
            # Seed the running k-th score with the best rows of the strongest list.
            strongest = lists[order[0], open_rows] * q[order[0]]
            seed = open_rows[np.argpartition(-strongest, k - 1)[:k]]
            threshold = int((q @ lists[:, seed]).min())
            # Essential: the lists that are left when the weakest ones can no longer add up to the threshold.
            essential = max(1, int(np.searchsorted(-(rest + floor), -threshold, "left")))
            take = order[:essential]
            partial = q[take] @ lists[take][:, open_rows] - least[take].sum() + floor
            done = essential
            while True:
                keep = partial + rest[done] >= threshold
                open_rows, partial = open_rows[keep], partial[keep]
                if done >= len(order) or len(open_rows) <= k:
                    break
                near = open_rows[np.argpartition(-partial, k - 1)[:k]]
                threshold = max(threshold, int((q @ lists[:, near]).min()))
                take = order[done : done + 4]
                partial = partial + q[take] @ lists[np.ix_(take, open_rows)] - least[take].sum()
                done += len(take)
        scores = (q @ lists[:, open_rows]).astype(np.int64)
        top = np.lexsort((self.ids[open_rows], -scores))[:k]
        return self.ids[open_rows][top], scores[top]


def by_scan(rows: Iterator[tuple[int, list[int]]], queries: Iterator[int], k: int) -> list[tuple[int, int, int, int]]:
    """Plain reference for tests: (query_id, rank, vec_id, score)."""
    rows = list(rows)
    vectors = dict(rows)
    out = []
    for q in queries:
        scored = sorted((-sum(x * y for x, y in zip(vectors[q], v, strict=False)), i) for i, v in rows if i != q)[:k]
        out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    return out
