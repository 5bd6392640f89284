"""The maintenance stream: batches of changes, a replayed batch, and expiry."""

from pyspark.sql import functions as F

from chronomill.plans import maintain as mt
from chronomill.plans import periodic as pr
from chronomill.plans.rules import parse_program
from chronomill.sources.store import facts_of
from chronomill.streaming.maintain_stream import ModelStream

PROGRAM = "p(x) :- PAST_SOME[0,2] q(x)."


def seen(pm):
    return sorted((r["pred"], r["a0"], r["lo"], r["hi"]) for r in pr.expanded(pm, -50, 50).collect())


def change(spark, op, facts):
    return facts_of(spark, facts).withColumn("op", F.lit(op))


def test_batches_replay_and_stream(spark, tmp_path):
    program = parse_program(PROGRAM)
    stream = ModelStream(program, f"{tmp_path}/m")
    stream.start(facts_of(spark, [("q", [i], 2 * i, 2 * i + 1) for i in range(4)]))
    first = change(spark, "remove", [("q", [0], 0, 1)]).unionByName(change(spark, "add", [("q", [7], 4, 5)]))
    second = change(spark, "add", [("q", [8], 6, 9)]).unionByName(change(spark, "remove", [("q", [7], 4, 4)]))
    first.write.parquet(f"{tmp_path}/in/a")
    running = stream.follow(spark.readStream.schema(first.schema).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in"), f"{tmp_path}/c")
    try:
        running.processAllAvailable()
        assert stream.version(spark) == 1
        second.write.parquet(f"{tmp_path}/in/b")
        running.processAllAvailable()
    finally:
        running.stop()
    assert stream.version(spark) == 2
    whole = facts_of(spark, [("q", [i], 2 * i, 2 * i + 1) for i in range(1, 4)] + [("q", [8], 6, 9)])
    cut = facts_of(spark, [("q", [7], 4, 5)]).withColumn("lo", F.col("lo") + 1)  # without the instant 4
    expected = seen(mt.rebuild(program, whole.unionByName(cut)))
    assert seen(stream.model(spark)) == expected
    stream.apply(first, 0)  # a batch that was done before
    assert stream.version(spark) == 2
    assert seen(stream.model(spark)) == expected


def test_expired_facts_leave(spark, tmp_path):
    program = parse_program(PROGRAM)
    stream = ModelStream(program, f"{tmp_path}/m", retention_cells=20)
    stream.start(facts_of(spark, [("q", [1], 0, 1), ("q", [2], 12, 13)]))
    stream.apply(change(spark, "add", [("q", [3], 20, 21)]), 0)
    expected = seen(mt.rebuild(program, facts_of(spark, [("q", [2], 12, 13), ("q", [3], 20, 21)])))
    assert seen(stream.model(spark)) == expected
