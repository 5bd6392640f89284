"""Vectorised word scanning of Arrow string columns, shared by the text operators.

All hashing works on UTF-8 bytes of whole texts. A column is walked in slices of about `SLICE_BYTES`
(one document at least), so the memory of a task does not depend on the number of rows of a batch.
"""

from __future__ import annotations

import os
import re
import tempfile
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 1 << 20
WORD = r"[^\x20\x09-\x0D]+"

# Odd 64-bit multipliers of the polynomial and of the finalising mix.
BASE = 0x9E3779B97F4A7C15 | 1
MIX_A = 0xBF58476D1CE4E5B9
MIX_B = 0x94D049BB133111EB

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
IDENTITY = np.arange(256, dtype=np.uint8)
LOWER = IDENTITY.copy()
LOWER[ord("A") : ord("Z") + 1] += 32
#: ASCII letters lower-cased, digits kept, other ASCII signs turned into spaces.
PLAIN = LOWER.copy()
PLAIN[[i for i in range(128) if not chr(i).isalnum()]] = 0x20

#: Bytes hashed at a time.
CHUNK = 1 << 18

_steps = np.full(CHUNK, BASE, np.uint64)
_steps[0] = 1
_powers = np.multiply.accumulate(_steps)
_steps[1:] = pow(BASE, -1, 1 << 64)
_inverse = np.multiply.accumulate(_steps)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(MIX_A)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(MIX_B)
    return x ^ (x >> np.uint64(31))


@dataclass
class Words:
    """Words of some documents: `hashes` of all words in order, `first[d]:first[d + 1]` those of document d; a word's
    bytes are table[data[start:end]]."""

    hashes: np.ndarray
    first: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    data: np.ndarray
    table: np.ndarray

    def prefixes(self, n_bytes: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of the first n_bytes bytes of words that are longer, and the positions of those words."""
        at = np.flatnonzero(self.ends - self.starts > n_bytes)
        s = self.starts[at]
        out = np.zeros(len(at), np.uint64)
        with np.errstate(over="ignore"):
            for j in range(n_bytes):
                out += (self.table[self.data[s + j]].astype(np.uint64) + np.uint64(1)) * _powers[j]
            return mix(out + np.uint64(n_bytes)), at

    def owner(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


def scan(data: np.ndarray, offsets: np.ndarray, table: np.ndarray = LOWER) -> Words:
    """Words of the documents data[offsets[d]:offsets[d + 1]], read in chunks: what is kept is 24 bytes for each word."""
    for forget in idle:
        forget()
    base = int(offsets[0])
    offsets = offsets.astype(np.int64) - base
    n = int(offsets[-1])
    data = data[base : base + n]
    parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    open_word: tuple[int, int] | None = None  # start and value of a word that reaches the end of the last chunk
    with np.errstate(over="ignore"):
        for low in range(0, n, CHUNK):
            b = table[data[low : low + CHUNK]]
            m = len(b)
            inside = ~_SPACE[b]
            cut = np.zeros(m + 1, bool)
            cut[offsets[np.searchsorted(offsets, low) : np.searchsorted(offsets, low + m, "right")] - low] = True
            edge = np.empty(m + 1, bool)  # where a stretch of equal kind may begin
            edge[0] = edge[-1] = True
            np.not_equal(inside[1:], inside[:-1], out=edge[1:-1])
            edge |= cut
            starts = np.flatnonzero(inside & edge[:-1])
            ends = np.flatnonzero(inside & edge[1:]) + 1
            sums = np.zeros(m + 1, np.uint64)
            np.cumsum((b.astype(np.uint64) + np.uint64(1)) * _powers[:m], out=sums[1:])
            values = (sums[ends] - sums[starts]) * _inverse[starts]
            starts, ends = starts + low, ends + low
            if open_word is not None:
                if len(starts) and starts[0] == low and not cut[0]:
                    shift = pow(BASE, low - open_word[0], 1 << 64)
                    values[0] = np.uint64((open_word[1] + shift * int(values[0])) & ((1 << 64) - 1))
                    starts[0] = open_word[0]
                else:
                    parts.append((np.array([open_word[0]]), np.array([low]), np.array([open_word[1]], np.uint64)))
                open_word = None
            if low + m < n and len(ends) and ends[-1] == low + m:
                open_word = (int(starts[-1]), int(values[-1]))
                starts, ends, values = starts[:-1], ends[:-1], values[:-1]
            parts.append((starts, ends, values))
        starts, ends = (np.concatenate([np.zeros(0, np.int64), *[p[i] for p in parts]]) for i in (0, 1))
        hashes = mix(np.concatenate([np.zeros(0, np.uint64), *[p[2] for p in parts]]))
    return Words(hashes, np.searchsorted(starts, offsets), starts, ends, data, table)


def slices(column: pa.Array, size: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of slices of a string column; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    column = pc.fill_null(column, "")
    if not len(column):
        return
    wide = pa.types.is_large_string(column.type)
    _, offset_buffer, data_buffer = column.buffers()
    offsets = np.frombuffer(offset_buffer, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data_buffer, np.uint8) if data_buffer is not None and data_buffer.size else np.zeros(0, np.uint8)
    row = 0
    while row < len(column):
        end = int(np.searchsorted(offsets, int(offsets[row]) + size, "right")) - 1
        end = min(len(column), max(end, row + 1))
        yield row, end, data, offsets[row : end + 1]
        row = end


def shingles(words: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k-word shingles (documents with 1 to k - 1 words: one, of all words) and the first of each document."""
    h, first = words.hashes, words.first
    counts = np.diff(first)
    per_doc = np.where(counts >= k, counts - k + 1, (counts > 0).astype(counts.dtype))
    out_first = np.concatenate([[0], np.cumsum(per_doc)])
    with np.errstate(over="ignore"):
        full = np.zeros(max(0, len(h) - k + 1), np.uint64)
        for j in range(k):
            full = full * np.uint64(BASE) + h[j : j + len(full)]
        owner = np.repeat(np.arange(len(counts)), per_doc)
        at = np.arange(out_first[-1]) - out_first[:-1][owner] + first[:-1][owner]
        out = np.zeros(out_first[-1], np.uint64)
        whole = counts[owner] >= k
        out[whole] = full[at[whole]]
        for i in np.flatnonzero(~whole):
            d = owner[i]
            value = np.uint64(counts[d])
            for x in h[first[d] : first[d + 1]]:
                value = value * np.uint64(BASE) + x
            out[i] = value
        return mix(out), out_first


def distinct_per_document(values: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each document, and the first of each."""
    parts = [np.unique(values[a:b]) for a, b in zip(first[:-1], first[1:], strict=True)]
    sizes = [len(p) for p in parts]
    return np.concatenate([np.zeros(0, values.dtype), *parts]), np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)]).astype(np.int64)


#: Rows of an Arrow batch; with the session's default of 10,000 a batch of long documents is a large part of a worker's memory.
BATCH_ROWS = 2000
#: What other operators keep in this worker process, to be called when a scan begins.
idle: list[Callable[[], None]] = []


def mapped(df: DataFrame, run, schema) -> DataFrame:
    """df.mapInArrow with batches of at most BATCH_ROWS rows (a setting of the running session, lowered here)."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(df.sparkSession.conf.get(key))
    if now <= 0 or now > BATCH_ROWS:
        df.sparkSession.conf.set(key, str(BATCH_ROWS))
    return df.mapInArrow(run, schema)


def scratch(spark: SparkSession, prefix: str) -> str:
    """A fresh path in the folder of spark.checkpoint.dir, which all executors share."""
    return f"{checkpoint_dir(spark)}/{prefix}-{os.urandom(8).hex()}"


def checkpoint_dir(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; where it is unset, a folder of this machine's if that is all there is (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir is not set: it must name a folder that all executors share")
        root = f"{tempfile.gettempdir()}/chronomill-checkpoints"
    return root


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written as a table in the shared folder and read again: cuts lineage and outlives executors."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def dropped(*frames: DataFrame) -> None:
    """Delete stored tables that nothing reads any more."""
    for df in frames:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df._stored_at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


#: Rows of a table that may be broadcast as the hot keys of a lookup.
HOT_KEYS = 20_000


def lookup(rows: DataFrame, values: DataFrame, keys: list[str], total: int, n: str = "n") -> DataFrame:
    """Inner join of rows with a table that has one row for each key and in n the number of rows with that key (which
    add up to total at most). Keys with more rows than total / HOT_KEYS (1000 at least), so HOT_KEYS of them at most,
    are broadcast, so that no task gets all rows of a key; the others are joined by shuffle."""
    bound = max(1000, total // HOT_KEYS)
    hot = F.broadcast(values.filter(F.col(n) > bound))
    rest = rows.join(hot.select(*keys), keys, "left_anti").join(values.filter(F.col(n) <= bound).hint("merge"), keys)
    return rows.join(hot, keys).unionByName(rest)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crc_bucket(column: str, n: int) -> Column:
    """crc32 of the value's text, modulo n."""
    return F.crc32(F.col(column).cast("string")) % n


def word_count(column: Column) -> Column:
    """Number of words of a text, as a long; null counts 0."""
    return F.coalesce(F.regexp_count(column, F.lit(WORD)), F.lit(0)).cast("long")
