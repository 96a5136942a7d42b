"""Synopses of event streams: additive counts by window, released once when a window closes.

A row is in one tumbling window, so each window may use its own budget; in sliding windows it is in
several, and the sensitivity grows with their number.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpcluster.functions.domain import Domain, normalize
from dpcluster.functions.noise import NoiseSource
from dpcluster.operators.centroids import Centroids
from dpcluster.operators.grid import GridSpec, cell_center, cell_id
from dpcluster.operators.lloyd import assign, moved, partial_sums

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
DOMAIN = Domain(("second", "value"), (0.0, 0.0), (86400.0, 500.0))


def points(events: DataFrame) -> DataFrame:
    """Events as points (second of the day, value), with time, id and user."""
    second = F.hour("ts") * 3600 + F.minute("ts") * 60 + F.second("ts")
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("second", second)
    return normalize(timed, DOMAIN, keep=("event_id", "ts", "user_id"))


def stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path)


def window_counts(pts: DataFrame, spec: GridSpec, width: str = "1 day", slide: str | None = None, late: str | None = None) -> DataFrame:
    """(start, cell, n) of batch or stream; ``late``: how long late rows are waited for."""
    pts = pts.withWatermark("ts", late) if late else pts
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return pts.groupBy(w.alias("w"), cell_id(["x0", "x1"], spec).alias("cell")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "cell", "n")


def release_windows(counts: DataFrame, spec: GridSpec, eps: float, source: NoiseSource, overlap: int = 1) -> DataFrame:
    """All cells of each window with noise keyed by window and cell: a replayed batch gives the same release."""
    starts = counts.select("start").distinct()
    every = starts.withColumn("cell", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(spec.cells - 1).cast("long"))))
    noise = source.laplace(overlap / eps, "window", F.unix_timestamp("start"), "cell")
    return every.join(counts, ["start", "cell"], "left").select("start", "cell", (F.coalesce("n", F.lit(0)) + noise).alias("n"), *cell_center("cell", spec))


def release_stream(counts: DataFrame, spec: GridSpec, eps: float, source: NoiseSource, path: str, checkpoint: str):
    """Writes each closed window once."""

    def put(batch: DataFrame, number: int) -> None:
        release_windows(batch, spec, eps, source).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return counts.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(put)


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    s = timed.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("s.start").alias("start"), "n")


def assign_stream(pts: DataFrame, released: Centroids) -> DataFrame:
    """Labels by released centroids; labels of private rows are no private output."""
    return assign(pts, ["x0", "x1"], released, "expr")


def dedupe(pts: DataFrame, late: str = "1 hour") -> DataFrame:
    return pts.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


class MiniBatch:
    """Centroids that follow a stream, without privacy: running sums, for foreachBatch."""

    def __init__(self, centroids: Centroids):
        self.centroids, self.sums = centroids, {}

    def __call__(self, batch: DataFrame, number: int = 0) -> None:
        cols = ["x0", "x1"]
        for row in partial_sums(assign(batch, cols, self.centroids, "expr"), cols).collect():
            old = self.sums.get(row["cluster"], {"n": 0.0, "s0": 0.0, "s1": 0.0})
            self.sums[row["cluster"]] = {"cluster": row["cluster"], **{c: old[c] + row[c] for c in ("n", "s0", "s1")}}
        self.centroids = moved(list(self.sums.values()), self.centroids)


def user_counts(pts: DataFrame) -> DataFrame:
    """Running counts by user, as a stateful operator."""

    def step(key, batches, state):
        import pandas as pd

        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    return pts.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long", "n long", "update", GroupStateTimeout.NoTimeout)


def join_streams(left: DataFrame, right: DataFrame, late: str = "1 hour", within: str = "10 minutes") -> DataFrame:
    """Events of one user in both streams that are close in time."""
    a = left.withWatermark("ts", late).select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = right.withWatermark("ts", late).select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return a.join(b, F.expr(f"ua = ub AND a <> b AND tb BETWEEN ta AND ta + INTERVAL {within}"))
