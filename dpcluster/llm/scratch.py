"""Intermediate tables in the shared checkpoint folder of the cluster.

Lineage is cut with written Parquet tables, which survive lost executors.  The folder is
``spark.checkpoint.dir``; only where that is unset (tests on one machine) a temporary one is made.
"""

from __future__ import annotations

import contextlib
import gc
import os
import sys
import tempfile
import uuid
from pathlib import Path

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

_FALLBACK: dict[str, str] = {}


def shared_folder(spark: SparkSession) -> str:
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "path" not in _FALLBACK:
        _FALLBACK["path"] = "file://" + tempfile.mkdtemp(prefix="dpcluster-")
    return _FALLBACK["path"]


class Scratch:
    """A folder of written tables that belong to one call of an operator.

    packed: their columns are compressed already."""

    def __init__(self, spark: SparkSession, name: str, packed: bool = False):
        self.spark = spark
        self.options = {"compression": "none", "parquet.enable.dictionary": "false"} if packed else {"compression": "zstd"}
        self.root = f"{shared_folder(spark)}/dpcluster/{name}-{uuid.uuid4().hex}"

    def write(self, df: DataFrame, label: str) -> DataFrame:
        path = f"{self.root}/{label}"
        df.write.options(**self.options).parquet(path)
        return self.read(label, df.schema)

    def read(self, label: str, schema) -> DataFrame:
        """A written table, as a relation of its own."""
        return self.spark.read.schema(schema).parquet(f"{self.root}/{label}")

    def release(self, last: bool = False) -> None:
        """Lets Spark delete the shuffle files of plans that nothing refers to any more.

        last: those of the last plan too, which Spark's listeners hold until they hear of another."""
        gc.collect()
        if last:
            self.spark.range(0, 1, 1, 1).collect()
            with contextlib.suppress(Py4JError):  # late listeners only keep the files longer
                self.spark._jsc.sc().listenerBus().waitUntilEmpty(10_000)
        self.spark._jvm.System.gc()

    def drop(self, label: str = "") -> None:
        """Deletes one table, or all, once nothing reads it any more."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        path = jvm.org.apache.hadoop.fs.Path(f"{self.root}/{label}" if label else self.root)
        path.getFileSystem(conf).delete(path, True)


def share_code(spark: SparkSession) -> None:
    """Lets Python workers import this package where it is not installed but its folder is visible."""
    home = str(Path(__file__).resolve().parents[2])
    environment = spark.sparkContext.environment
    known = environment.get("PYTHONPATH", "")
    if home not in known.split(os.pathsep):
        environment["PYTHONPATH"] = os.pathsep.join(x for x in (home, known) if x)
    if home not in sys.path:
        sys.path.insert(0, home)
