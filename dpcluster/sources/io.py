"""Readers and writers with declared schemas, and round trips through each format.

Databases and queues need no code here: Spark's own ``jdbc`` source (partitionColumn, lowerBound,
upperBound, numPartitions) and ``kafka`` source give the same DataFrames, where their jars are there.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from dpcluster.operators.centroids import as_table

FORMATS = ("parquet", "csv", "json", "orc", "text")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors see; only a session on one machine may do without a setting."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder and not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{folder.rstrip('/') if folder else 'file://' + tempfile.gettempdir()}/dpcluster-core"


def save_centroids(spark: SparkSession, path: str, centroids) -> None:
    as_table(spark, [centroids]).coalesce(1).write.mode("overwrite").parquet(path)


def load_centroids(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("run long, j int, c array<double>").parquet(path)


def write(df: DataFrame, path: str, kind: str = "parquet", **options) -> None:
    if kind not in FORMATS:
        raise ValueError(f"one of {FORMATS}")
    df.write.mode("overwrite").format(kind).options(**({"header": "true"} if kind == "csv" else {}), **options).save(path)


def read(spark: SparkSession, path: str, schema, kind: str = "parquet", **options) -> DataFrame:
    return spark.read.schema(schema).format(kind).options(**({"header": "true"} if kind == "csv" else {}), **options).load(path)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    path = f"{shared_folder(df.sparkSession)}/{kind}-{uuid.uuid4().hex}"
    write(df, path, kind)
    return read(df.sparkSession, path, df.schema, kind)
