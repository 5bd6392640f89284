"""Deletion of line runs that repeat earlier text, by winnowing over line hashes (DataFrame functions only).

Lines with a word are hashed. A line is deleted if it lies in a run of lines with `MIN_WORDS` words or more that stands
somewhere before (in the order of document ids, then of lines).

Fingerprints: the window of a line is the shortest run from it on with `MIN_WORDS` words; the least line hash of each
window is selected (the last place among equals), so neighbouring windows mostly select the same line. Two equal runs of
`MIN_WORDS` words begin with equal windows and so share a fingerprint. Fingerprints that occur once are done with.

Matches: positions of the others are extended both ways, to the shortest runs forward from a line and backward to a line
that contain them and have enough words. Such a run is joined with its earliest occurrence by the hash of its lines; a
later one is deleted. In any longer repeated run each line lies in one of these, whatever the lengths of its lines: the
run forward from a line if it ends within, else the one backward to it, else the one forward from the first line. So the
length of matches is not bounded, and every earlier occurrence counts.

Edge cases: null texts stay null and empty ones empty; lines without a word are kept and do not break runs; rows with
equal id and text are one document; null ids come first; a document may lose all its lines and stays with what is
left; equal hashes of two different runs (64 and 32 bits) are taken for equal runs; all columns pass (names with a
leading _ld_ are used inside; of columns called removed_lines and n_lines the operator's own replace those of the input).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textscan as ts

MIN_WORDS = 50
LEAST_ID = -(1 << 63)
DOC = ["_ld_id", "_ld_hash"]


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("_ld_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST_ID))).withColumn("_ld_hash", F.coalesce(F.xxhash64("text"), F.lit(0)))


def lines(docs: DataFrame) -> DataFrame:
    """One row for each line with a word: document, place, hash, number of words."""
    cut = _keyed(docs).filter(F.col("text").isNotNull()).select(*DOC, F.posexplode(F.split("text", "\n", -1)).alias("place", "line"))
    counted = cut.select(*DOC, "place", F.xxhash64("line").alias("h"), ts.word_count(F.col("line")).cast("int").alias("n")).filter("n > 0")
    return counted.repartition(*DOC).dropDuplicates([*DOC, "place"])


def _forward(min_words: int):
    """From a line to where its window has enough words (over `before`, the words before a line)."""
    return Window.partitionBy(*DOC).orderBy("before").rangeBetween(0, min_words - 1)


def _counted(rows: DataFrame) -> DataFrame:
    before = F.coalesce(F.sum("n").over(Window.partitionBy(*DOC).orderBy("place").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("before", before.cast("long"))


def fingerprints(rows: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """Selected lines: document, place and hash of the least line of each window with min_words words."""
    own = _forward(min_words)
    found = _counted(rows).select(*DOC, F.sum("n").over(own).alias("words"), F.min(F.struct("h", -F.col("place"))).over(own).alias("least"))
    return found.filter(F.col("words") >= min_words).select(*DOC, (-F.col("least.col2")).alias("place"), F.col("least.h").alias("h")).distinct()


def runs(rows: DataFrame, positions: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """Shortest runs forward from and backward to a line, with min_words words and a line in positions (document,
    place): first and last place, and two hashes of the lines."""
    within = rows.join(positions.select(*DOC).distinct(), DOC, "left_semi")
    marked = within.withColumn("mark", F.lit(0)).unionByName(positions.select(*DOC, "place", F.lit(None).cast("long").alias("h"), F.lit(0).alias("n"), F.lit(1).alias("mark")))
    here = Window.partitionBy(*DOC).orderBy("place").rangeBetween(0, 0)
    placed = _counted(marked.withColumn("mark", F.max("mark").over(here)).filter("n > 0")).withColumn("after", F.col("before") + F.col("n"))
    ahead, back = _forward(min_words), Window.partitionBy(*DOC).orderBy("after").rangeBetween(1 - min_words, 0)

    def run(w) -> F.Column:
        return F.struct(F.min("place").over(w).alias("a"), F.max("place").over(w).alias("b"), F.sum("n").over(w).alias("words"), F.max("mark").over(w).alias("mark"), F.collect_list("h").over(w).alias("hashes"))

    both = placed.select(*DOC, run(ahead).alias("f"), run(back).alias("g")).select(*DOC, F.explode(F.array("f", "g")).alias("r"))
    found = both.filter((F.col("r.words") >= min_words) & (F.col("r.mark") == 1))
    return found.select(*DOC, "r.a", "r.b", F.xxhash64("r.hashes").alias("q"), F.hash("r.hashes").alias("q2"))


def repeats(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """Document and the places of its lines to delete, in order."""
    rows = ts.stored(lines(docs), "lines")
    prints = ts.stored(fingerprints(rows, min_words), "fingerprints")
    total = prints.count()
    again = prints.groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    found = ts.stored(runs(rows, ts.lookup(prints, again, ["h"], total).drop("n"), min_words), "runs")
    first = found.groupBy("q", "q2").agg(F.min(F.struct(*DOC, "a")).alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    later = ts.lookup(found, first, ["q", "q2"], found.count()).filter(F.struct(*DOC, "a") > F.col("first"))
    # Lines within a later run: those with an open run in the running sum of first and last places.
    ends = F.array(F.struct(F.col("a").alias("place"), F.lit(1).alias("d")), F.struct((F.col("b") + 1).alias("place"), F.lit(-1).alias("d")))
    steps = ts.stored(later.select(*DOC, F.explode(ends).alias("e")).groupBy(*DOC, "e.place").agg(F.sum("e.d").cast("int").alias("d")), "steps")
    touched = rows.join(steps.select(*DOC).distinct(), DOC, "left_semi").select(*DOC, "place", F.lit(0).alias("d"), F.lit(True).alias("line"))
    so_far = Window.partitionBy(*DOC).orderBy("place").rangeBetween(Window.unboundedPreceding, 0)
    gone = touched.unionByName(steps.withColumn("line", F.lit(False))).withColumn("open", F.sum("d").over(so_far)).filter("line and open > 0")
    return gone.groupBy(*DOC).agg(F.sort_array(F.collect_list("place")).alias("_ld_gone"))


def without_repeats(docs: DataFrame, min_words: int = MIN_WORDS, keep_places: bool = False) -> DataFrame:
    """docs with later repeated runs taken out of text; keep_places adds removed_lines array<int> and n_lines."""
    joined = _keyed(docs).join(repeats(docs, min_words), DOC, "left")
    # A flag for each line up to the last deleted one, so that a line is looked up by its place.
    gaps = F.transform("_ld_gone", lambda p, i: F.concat(F.array_repeat(F.lit(False), p - F.when(i > 0, F.get("_ld_gone", i - 1)).otherwise(-1) - 1), F.array(F.lit(True))))
    joined = joined.withColumn("_ld_flags", F.flatten(gaps))
    kept = F.filter(F.split("text", "\n", -1), lambda x, i: ~F.coalesce(F.get("_ld_flags", i), F.lit(False)))
    text = F.when(F.col("_ld_gone").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))
    own = {"text": text}
    if keep_places:
        own |= {"removed_lines": F.coalesce("_ld_gone", F.array().cast("array<int>")), "n_lines": F.coalesce(F.size(F.split("text", "\n", -1)), F.lit(0))}
    columns = [c for c in docs.columns if c == "text" or c not in own]
    return joined.select(*[own[c].alias(c) if c in own else F.col(c) for c in [*columns, *[c for c in own if c != "text"]]])
