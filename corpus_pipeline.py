"""A corpus pipeline: what a classifier rejects goes, near copies go, secrets are masked, sources are mixed, and the rest is packed.

Every stage takes (spark, docs, sf_dir); its result is written as Parquet and read again as the next one's documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpcluster.llm import jaccard, mixing, packing, quality, secrets
from dpcluster.llm.scratch import Scratch
from dpcluster.llm.tokens import tokenizer_path


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier learned from the labels doesn't reject."""
    return quality.accepted(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: five words, similarity of 0.8 or more."""
    return jaccard.keep_first(docs, n=5, percent=80)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with every secret masked."""
    return secrets.redact(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix of sources takes it; the classifier's scores weigh documents within a source."""
    scored = quality.with_scores(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), "__quality")
    return mixing.copies(scored, quality=F.col("__quality")).drop("__quality")


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences whose lengths are powers of two, with their token ids."""
    return packing.pack(docs, tokenizer_path("word_bpe_49k.json"), with_ids=True)


STAGES = [("quality classifier", quality_classifier), ("n-gram Jaccard join", near_duplicates), ("secret scans", secret_scan), ("mixing sources", source_mix), ("packing", packed)]

#: A learned classifier and a tokenizer can't be said in SQL; tests/llm hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents; what lies between is written to the shared folder."""
    tables, docs = Scratch(spark, "pipeline"), spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = tables.write(stage(spark, docs, sf_dir), f"stage_{i}")
    return docs
