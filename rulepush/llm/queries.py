"""Queries of the training-data operators, one for each, and their SQL where SQL can say it."""

from __future__ import annotations

import public_tokenizers

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, lines, mixing, neardup, ngram, records, rules, suffixes, tokenization, vafile
from .common import table


def token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenization.count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return records.token_records(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    asked = vectors.filter(F.col("vec_id") % 100 == 0).select(F.col("vec_id").alias("query_id"), "embedding")
    return vafile.top_k(vectors, asked)


TOP_K_ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, v.vec_id, list_dot_product(q.e, v.e)::BIGINT AS score
  FROM v AS q JOIN v ON q.vec_id <> v.vec_id WHERE q.vec_id % 100 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""

QUERIES = {
    "op1_token_counts": token_counts,
    "op2_source_mix": mixing.query,
    "op3_token_records": token_records,
    "op4_bpe_round_trip": bpe_round_trip,
    "op5_quality_model": ngram.query,
    "op6_quality_rules": rules.query,
    "op7_exact_top_k": exact_top_k,
    "op8_near_duplicates": neardup.query,
    "op9_line_dedup": lines.query,
    "op9_every_line_dedup": lines.every_line,
    "op10_repeated_strings": suffixes.query,
}
ORACLES = {"op7_exact_top_k": TOP_K_ORACLE, "op9_line_dedup": lines.ORACLE, "op9_every_line_dedup": lines.EVERY_LINE_ORACLE}
