"""Tables, and frames kept in the shared checkpoint folder."""

from __future__ import annotations

import json
import os
import re
import tempfile
import time

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; where it is unset, one of this machine's if that is all there is (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir is not set: it must name a folder that all executors share")
        root = f"{tempfile.gettempdir()}/chronomill-checkpoints"
    return root


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written as a table in the shared folder and read again: cuts lineage and outlives executors. Facts are written by
    predicate, so that a reader of one skips the pages of others."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{os.urandom(8).hex()}"
    (df.sortWithinPartitions("pred") if "pred" in df.columns else df).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored_with(df: DataFrame, name: str, metrics: dict[str, Column]) -> tuple[DataFrame, dict]:
    """stored, and aggregates of df taken while it is written."""
    seen = Observation(f"{name}-{os.urandom(4).hex()}")
    out = stored(df.observe(seen, *[c.alias(k) for k, c in metrics.items()]), name)
    return out, seen.get


ARGS = ("a0", "a1", "a2")


def fact_columns() -> list[str]:
    return ["pred", *ARGS, "lo", "hi"]


def facts(df: DataFrame, pred: str, args: list[str | Column], lo: Column, hi: Column) -> DataFrame:
    """Fact rows of a predicate; constants are kept as text, rows with a null constant or end are rejected."""
    if len(args) > len(ARGS):
        raise ValueError(f"at most {len(ARGS)} arguments: {pred}")
    cols = [(F.col(a) if isinstance(a, str) else a).cast("string") for a in args]
    named = [c.alias(n) for c, n in zip(cols + [F.lit("")] * (len(ARGS) - len(args)), ARGS, strict=True)]
    out = df.select(F.lit(pred).alias("pred"), *named, lo.cast("long").alias("lo"), hi.cast("long").alias("hi"))
    return out.na.drop().filter("lo <= hi")


def facts_at(df: DataFrame, pred: str, args: list[str | Column], tick: Column, hold: int = 0, end_open: bool = False) -> DataFrame:
    """Facts that hold from a tick on: at it alone, or for `hold` ticks more."""
    return facts(df, pred, args, 2 * tick, 2 * (tick + hold) - int(end_open))


def rigid(df: DataFrame, pred: str, args: list[str | Column], first: int, last: int) -> DataFrame:
    """Facts that hold on the whole (bounded) span of ticks."""
    return facts(df, pred, args, F.lit(2 * first), F.lit(2 * last))


def union_all(frames: list[DataFrame]) -> DataFrame:
    """By halves: a plan is analysed for each union in it, so a chain of them costs the square of its length."""
    if len(frames) < 3:
        return frames[0].unionByName(frames[1]) if frames[1:] else frames[0]
    half = len(frames) // 2
    return union_all(frames[:half]).unionByName(union_all(frames[half:]))


def no_facts(spark: SparkSession) -> DataFrame:
    return spark.range(0).select(*[F.lit("").alias(c) for c in ("pred", *ARGS)], F.lit(0).cast("long").alias("lo"), F.lit(0).cast("long").alias("hi"))


def facts_of(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Small literal fact sets for tests and examples: (pred, args, start, end[, start_open, end_open])."""
    out = []
    for pred, args, start, end, *opened in rows:
        a, b = opened or (False, False)
        cells = (2 * start + int(a), 2 * end - int(b))
        texts = [pred, *[str(x) for x in args], *[""] * (len(ARGS) - len(args))]
        out.append(F.struct(*[F.lit(x).alias(n) for n, x in zip(fact_columns(), texts, strict=False)], *[F.lit(c).cast("long").alias(n) for n, c in zip(("lo", "hi"), cells, strict=True)]))
    return spark.range(1).select(F.inline(F.array(*out))) if out else no_facts(spark)


def append_delta(df: DataFrame, op: str, version: int, path: str) -> None:
    """Append removals or additions to a log of changes."""
    df.select(F.lit(version).alias("version"), F.lit(op).alias("op"), "*").write.mode("append").parquet(path)


def append_text(spark: SparkSession, path: str, payload: dict) -> None:
    """Append a version's row; rows written before stay, so that a reader or a crash meets the last whole one."""
    row = json.dumps(payload | {"at": time.time()})
    spark.createDataFrame([(row,)], "value string").coalesce(1).write.mode("append").text(path)


def latest_text(spark: SparkSession, path: str) -> dict:
    """The row of the greatest version, of several the one written last."""
    at = lambda name: F.get_json_object("value", f"$.{name}").cast("double")
    return json.loads(spark.read.text(path).orderBy(at("version").desc(), at("at").desc()).first()[0])
