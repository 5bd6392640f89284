"""Maintenance of a model by a stream of changes: batch id is model version, so a batch that is replayed is skipped."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import maintain as mt
from ..plans import periodic as pr
from ..plans.rules import Program
from ..sources.store import append_delta, fact_columns, stored


class ModelStream:
    """Keeps explicit facts and their model in a folder; changes are fact rows with a column op (`add` or `remove`)."""

    def __init__(self, program: Program, folder: str, retention_cells: int | None = None) -> None:
        self.program, self.folder, self.retention = program, folder, retention_cells

    def start(self, explicit: DataFrame) -> None:
        pm = mt.rebuild(self.program, explicit)
        explicit.write.mode("overwrite").parquet(f"{self.folder}/explicit/v0")
        pr.save_model(pm, f"{self.folder}/model", 0)

    def version(self, spark) -> int:
        return pr.latest_text(spark, f"{self.folder}/model/current")["version"]

    def model(self, spark) -> pr.PeriodicModel:
        return pr.load_model(spark, f"{self.folder}/model")

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        spark, version = batch.sparkSession, batch_id + 1
        now = self.version(spark)
        if version <= now:
            return
        changes = stored(batch.select("op", *fact_columns()), "batch")
        explicit = spark.read.parquet(f"{self.folder}/explicit/v{now}")
        removed, added = (changes.filter(F.col("op") == op).drop("op") for op in ("remove", "add"))
        if self.retention is not None:
            # What ends before the horizon leaves the explicit facts: a removal like any other.
            last = explicit.unionByName(added).agg(F.max("hi")).first()[0] or 0
            removed = removed.unionByName(explicit.filter(F.col("hi") < last - self.retention))
        for op, df in (("remove", removed), ("add", added)):
            append_delta(df, op, version, f"{self.folder}/log")
        target, pm, _ = mt.maintain(self.program, explicit, self.model(spark), removed, added)
        target.write.mode("overwrite").parquet(f"{self.folder}/explicit/v{version}")
        pr.save_model(pm, f"{self.folder}/model", version)

    def follow(self, changes: DataFrame, checkpoint: str):
        """A running query over a stream of changes."""
        return changes.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint).start()


def register_views(pm: pr.PeriodicModel, lo: int, hi: int, preds: list[str]) -> None:
    """A temporary view of the expanded model for each predicate."""
    facts = pr.expanded(pm, lo, hi)
    for p in preds:
        facts.filter(F.col("pred") == p).drop("pred").createOrReplaceTempView(f"model_{p}")
