"""Measures of results and of runs."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

RESULT = "dataset string, method string, eps double, init int, noise_run int, nicv double, seconds double, scans int"


def summarize(results: DataFrame) -> DataFrame:
    """Means over repetitions, with spread."""
    return results.groupBy("dataset", "method", "eps").agg(F.avg("nicv").alias("nicv"), F.stddev_samp("nicv").alias("sd"), (F.stddev_samp("nicv") / F.sqrt(F.count("*"))).alias("se"), F.count("*").alias("runs"), *([F.avg("seconds").alias("seconds")] if "seconds" in results.columns else []))


def nicv_gap(results: DataFrame, baseline: str = "baseline") -> DataFrame:
    base = results.where(F.col("method") == baseline).groupBy("dataset").agg(F.min("nicv").alias("base"))
    return results.where(F.col("method") != baseline).join(base, "dataset").withColumn("gap", F.col("nicv") - F.col("base"))


def mse_parts(df: DataFrame, est: str, act: str) -> DataFrame:
    """mse = variance + squared bias of the error."""
    e = F.col(est) - F.col(act)
    return df.agg(F.avg(e * e).alias("mse"), F.var_pop(e).alias("variance"), (F.avg(e) * F.avg(e)).alias("bias2"))


def centroid_mse_empirical(keys: DataFrame, s: list[float], c: float, scale: float, source=None) -> DataFrame:
    """The mean squared error of noisy sums over a noisy count, by simulation: what the first-order form approximates.

    keys: a draw for each id."""
    from dpcluster.functions.noise import NoiseSource

    source, error = source or NoiseSource("centroid-mse"), F.lit(0.0)
    n = F.lit(float(c)) + source.laplace(scale, "count", "id")
    for i, x in enumerate(s):
        error = error + F.pow((F.lit(float(x)) + source.laplace(scale, f"sum-{i}", "id")) / n - x / c, 2)
    return keys.select(error.alias("e")).agg(F.avg("e").alias("mse"))


def iterations_to(trace: DataFrame, base: float, tolerance: float = 0.01) -> DataFrame:
    """First iteration of each run that is within the tolerance of a baseline."""
    return trace.where(F.col("nicv") <= base * (1 + tolerance)).groupBy("run").agg(F.min("iteration").alias("iteration"))


def purity(assigned: DataFrame, label: str = "label") -> DataFrame:
    """Share of points in the most common label of their cluster."""
    n = assigned.groupBy("cluster", label).count()
    best = n.withColumn("i", F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("count"), label))).where("i = 1")
    return best.agg(F.sum("count").alias("most")).join(n.agg(F.sum("count").alias("rows"))).select((F.col("most") / F.col("rows")).alias("purity"))


def timed(fn):
    t = time.perf_counter()
    out = fn()
    return out, time.perf_counter() - t
