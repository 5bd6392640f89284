"""Queries of this subpackage, for the registry: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import curriculum, importance, langprofile, linedup, maxscore, minmax, pieces, sketch, surrogates, toxicity
from . import textscan as ts

TOKENIZER = "piece_bpe_32k.model"
SURROGATE_KEY = "chronomill"


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_importance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return importance.judged(ts.table(spark, sf_dir, "documents"), ts.table(spark, sf_dir, "labels"))


def op2_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode_documents(ts.table(spark, sf_dir, "documents"), tokenizer_path())


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cleaned = linedup.without_repeats(ts.table(spark, sf_dir, "documents"), keep_places=True)
    return cleaned.select("doc_id", "n_lines", F.size("removed_lines").alias("n_removed"), "removed_lines", "text")


def op4_scaled_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch.compare_with_next(ts.table(spark, sf_dir, "documents"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = ts.table(spark, sf_dir, "documents")
    held_out = ts.crc_bucket("doc_id", 4) == 2
    model = toxicity.learn(docs, ts.table(spark, sf_dir, "labels"), ~held_out)
    return toxicity.score(docs, model).select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op6_maxscore(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxscore.top_k(ts.table(spark, sf_dir, "embeddings"), F.col("id") % 50 == 0, k=5)


OP6_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT a.vec_id AS query_id, b.vec_id, list_inner_product(a.e, b.e)::BIGINT AS score
  FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0
), r AS (
  SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s
) SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = ts.table(spark, sf_dir, "documents")
    held_out = ts.crc_bucket("doc_id", 5) == 0
    profiles = langprofile.learn(docs, ~held_out)
    return langprofile.identify(docs, profiles).select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "lang_pred", "score")


def op8_minmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minmax.groups(ts.table(spark, sf_dir, "documents"), k=3, percent=85)


def op9_curriculum(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curriculum.mix(ts.table(spark, sf_dir, "documents"))


def op10_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = ts.table(spark, sf_dir, "documents")
    done = surrogates.replaced(docs, SURROGATE_KEY, with_entities=True)
    return done.select("doc_id", F.size("entities").alias("n_entities"), F.transform("entities", lambda e: e["kind"]).alias("kinds"), F.transform("entities", lambda e: e["surrogate"]).alias("surrogates"), "text")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_importance, op2_piece_codec, op3_line_dedup, op4_scaled_sketch, op5_toxicity, op6_maxscore, op7_language, op8_minmax, op9_curriculum, op10_surrogates)}


def oracle_sql() -> dict[str, str]:
    return {"op6_maxscore": OP6_SQL}
