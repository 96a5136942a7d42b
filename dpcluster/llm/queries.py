"""The ten operators over whole tables, with production parameters, and the SQL that some have."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpcluster.llm import bit_mixing, edit_counts, jaccard, mixing, multi_index, packing, pivots, quality, secrets, wavelet
from dpcluster.llm.scratch import Scratch
from dpcluster.llm.tokens import tokenizer_path


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multi_index.search_table(_table(spark, sf_dir, "embeddings"), every=100, k=10)


def op2_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights of documents are the scores of the quality classifier."""
    scored = quality.with_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"), "__quality")
    return mixing.mix(scored, quality=F.col("__quality"))


def op3_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pivots.search_table(_table(spark, sf_dir, "embeddings"), every=20, k=20)


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


def op5_bit_mixing_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bit_mixing.score(_table(spark, sf_dir, "documents"), most=bit_mixing.ALL)


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op7_edit_aware_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edit_counts.count_with_edits(_table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))


def op8_wavelet_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{Scratch(spark, 'wavelet').root}/shards"
    wavelet.write(_table(spark, sf_dir, "documents"), path, tokenizer_path("byte_bpe_50k.json"))
    return wavelet.read(spark, path)


def op9_shingle_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.groups(_table(spark, sf_dir, "documents"), n=3, percent=90)


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(_table(spark, sf_dir, "documents"))


def queries():
    return {f.__name__: f for f in (op1_nearest_neighbours, op2_source_mix, op3_exact_top_k, op4_packing, op5_bit_mixing_scores, op6_quality, op7_edit_aware_counts, op8_wavelet_shards, op9_shingle_groups, op10_secrets)}


#: Exact searches are plain SQL over whole tables; the mix is too, but for the order of its keys.
TOP_K_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64.0 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
  FROM embeddings WHERE embedding IS NOT NULL
),
s AS (
  SELECT q.vec_id AS query_id, r.vec_id AS vec_id, CAST(list_dot_product(CAST(q.e AS DOUBLE[]), CAST(r.e AS DOUBLE[])) AS BIGINT) AS score
  FROM v q JOIN v r ON q.vec_id <> r.vec_id WHERE q.vec_id % 20 = 0
),
k AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM k WHERE rank <= 20
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_exact_top_k": TOP_K_SQL}
