"""The published experiments on the stand-ins, with as many repetitions as asked for.

Each gives a table of runs; means are taken by ``metrics.summarize``.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource
from dpcluster.operators import block_average as blocks
from dpcluster.operators import evolve as ev
from dpcluster.operators.centroids import init_sets
from dpcluster.operators.grid import grid_spec, cells_general, range_count, range_count_exact, release_grid, fixed_boxes, GridSpec
from dpcluster.operators.grid_kmeans import grid_kmeans_many
from dpcluster.operators.lloyd import best_of, grouped, lloyd_many, nicv, nicv_many
from dpcluster.operators.noisy_lloyd import noisy_lloyd_many
from dpcluster.operators.two_stage import two_stage_many
from dpcluster.plans.metrics import RESULT, timed
from dpcluster.sources.workloads import WORKLOADS, gaussian_clusters

THETAS = (1, 2, 5, 10, 20, 50, 100)
EPSILONS = (0.05, 0.1, 0.2, 0.4, 0.7, 1.0, 1.5, 2.0)


@dataclass(frozen=True)
class Protocol:
    """Repetitions; ``published`` has those of the reference, ``quick`` fits a test."""

    inits: int = 30
    noises: int = 100
    repeats: int = 100
    synopses: int = 10
    max_cells: int | None = None
    pool: int = 200

    @staticmethod
    def quick() -> Protocol:
        return Protocol(3, 3, 2, 2)


METHODS = ("noisy_lloyd", "evolve", "block_average", "block_3k", "grid_kmeans", "two_stage")


def runs(df: DataFrame, cols: list[str], k: int, n: int, eps: float, method: str, p: Protocol, seed: int = 0, theta: float = 10.0) -> list[tuple[int, list]]:
    """(scans, centroids) of each repetition."""
    sets, src = init_sets(p.inits, k, len(cols), seed), lambda i: NoiseSource(f"exp-{seed}-{i}")
    if method == "noisy_lloyd":
        return [(5, c) for c in noisy_lloyd_many(df, cols, sets, p.noises, eps, source=src(0))]
    if method == "grid_kmeans":
        return [(1, c) for c in grid_kmeans_many(df, cols, eps, n, sets, p.synopses, src(0), theta=theta, max_cells=p.max_cells)]
    if method in ("two_stage", "refine"):
        return [(2, c) for c in two_stage_many(df, cols, k, eps, n, p.synopses, p.synopses, src(0), p.inits, seed, "refine" if method == "refine" else None, p.max_cells)]
    if method == "evolve":
        return [(c.stats["scans"], c.centroids) for c in ev.evolve_many(df, cols, k, eps, n, p.repeats, p.pool, source=src(0), seed=seed)]
    return [(2, blocks.block_average(df, cols, k, eps, n, "3k" if method == "block_3k" else "power", source=src(i), seed=i).centroids) for i in range(p.repeats)]


def compare(spark: SparkSession, data: dict[str, tuple[DataFrame, int, int]], eps: list[float], methods, p: Protocol) -> DataFrame:
    """data: name -> (points, d, k).  One row a run, and one of the baseline for each table."""
    out: list[tuple] = []
    for name, (df, d, k) in data.items():
        cols = [f"x{i}" for i in range(d)]
        df = df.select(*cols).persist()
        n = df.count()
        out.append((name, "baseline", 0.0, 0, 0, float(best_of(df, cols, init_sets(p.inits, k, d))[1]), 0.0, 0))
        for e in eps:
            for method in methods:
                found, seconds = timed(lambda m=method, e=e: runs(df, cols, k, n, e, m, p))
                values = nicv_many(df, cols, [c for _, c in found])
                out += [(name, method, float(e), 0, i, float(v), seconds / len(found), s) for i, ((s, _), v) in enumerate(zip(found, values))]
        df.unpersist()
    return spark.createDataFrame(out, RESULT)


def stand_ins(spark: SparkSession, sf_dir: str, which) -> dict:
    return {w: (WORKLOADS[w].points(spark, sf_dir), WORKLOADS[w].d, WORKLOADS[w].k) for w in which}


def generated(spark: SparkSession, ds, ks, n: int = 10_000, sigma: float = 0.08) -> dict:
    return {f"d{d}k{k}": (gaussian_clusters(spark, n, d, k, sigma, 100 * d + k), d, k) for d in ds for k in ks}


def heatmap(results: DataFrame, ks) -> DataFrame:
    """Gap to the baseline, a row for each d and method, a column for each k."""
    from dpcluster.plans.metrics import nicv_gap

    gap = nicv_gap(results).withColumns({"d": F.regexp_extract("dataset", r"d(\d+)k", 1).cast("int"), "k": F.regexp_extract("dataset", r"k(\d+)$", 1).cast("int")})
    return gap.groupBy("method", "d").pivot("k", list(ks)).agg(F.avg("gap"))


def theta_sweep(spark: SparkSession, data: dict, eps: float, p: Protocol, thetas=THETAS) -> DataFrame:
    out: list[tuple] = []
    for name, (df, d, k) in data.items():
        cols = [f"x{i}" for i in range(d)]
        df = df.select(*cols).persist()
        n = df.count()
        for t in thetas:
            sets = [c for _, c in runs(df, cols, k, n, eps, "grid_kmeans", p, theta=float(t))]
            out.append((name, float(t), sum(nicv_many(df, cols, sets)) / len(sets)))
        df.unpersist()
    return spark.createDataFrame(out, "dataset string, theta double, nicv double")


def block_sizes(spark: SparkSession, df: DataFrame, d: int, k: int, eps: float, exponents, p: Protocol) -> DataFrame:
    cols = [f"x{i}" for i in range(d)]
    df = df.select(*cols).persist()
    n = df.count()
    best, _ = best_of(df, cols, init_sets(p.inits, k, d))
    rows = blocks.block_error_sources(df, cols, k, eps, n, best, exponents, NoiseSource("blocks"), lambda c: nicv(df, cols, c))
    return spark.createDataFrame([(float(a), int(b), *map(float, v)) for a, b, *v in rows], "exponent double, blocks int, total double, aggregation double, noise double")


def convergence(spark: SparkSession, df: DataFrame, d: int, k: int, n_inits: int, rounds: int = 12) -> DataFrame:
    """NICV by iteration: the mean over starts of plain rounds, and non-private evolution.

    Equal points are grouped once; a table that ``grouped`` made is taken as it is."""
    cols = [f"x{i}" for i in range(d)]
    df = df if "__rows" in df.columns else grouped(df, cols, "__rows").persist()
    n = df.agg(F.sum("__rows")).first()[0]
    _, costs, _ = lloyd_many(df, cols, init_sets(n_inits, k, d), rounds, weight="__rows")
    rows = [("lloyd", i, sum(c[min(i, len(c) - 1)] for c in costs) / len(costs)) for i in range(rounds)]
    evolved = ev.evolve(df, cols, k, 1.0, n, rounds=rounds, private=False, weight="__rows")
    rows += [("evolve", i, float(v) / n) for i, v in enumerate(evolved.trace)]
    return spark.createDataFrame([(m, i, float(v)) for m, i, v in rows], "run string, iteration int, nicv double")


def range_accuracy(spark: SparkSession, df: DataFrame, d: int, eps: float, ms, n_boxes: int = 50) -> DataFrame:
    """Mean squared error of range counts by the intervals of the grid."""
    cols, boxes, n = [f"x{i}" for i in range(d)], fixed_boxes(spark, d, n_boxes), df.count()
    truth, out = range_count_exact(df, cols, boxes), None
    for m in ms:
        got = range_count(release_grid(df, cols, eps, n, spec=GridSpec((m,) * d), source=NoiseSource(f"range-{m}")), boxes)
        row = truth.join(got, "qid", "left").agg(F.lit(m).alias("m"), F.avg(F.pow(F.coalesce("est", F.lit(0.0)) - F.col("n"), 2)).alias("mse"))
        out = row if out is None else out.unionAll(row)
    return out.withColumn("rule", F.lit(float(math.floor(cells_general(n, eps, d) ** (1 / d) + 0.5))))


def count_bias(spark: SparkSession, eps_list, releases: int = 10, n: int = 9000) -> DataFrame:
    """How raw, rounded and truncated counts move centroids: clusters in one corner, a common start."""
    from dpcluster.operators.centroids import packed_init
    from dpcluster.operators.grid_kmeans import cluster_synopsis

    corner = gaussian_clusters(spark, n, 2, 3, 0.08, 11).select(*(F.greatest(F.lit(-1.0), (F.col(c) * 0.3 - 0.65)).alias(c) for c in ("x0", "x1")))
    corner = corner.persist()
    truth = sorted(best_of(corner, ["x0", "x1"], [[[x * 0.3 - 0.65 for x in c] for c in packed_init(3, 2, 11, tries=100, rounds=14)[0]]])[0])
    out = []
    for eps in eps_list:
        for i in range(releases):
            syn = release_grid(corner, ["x0", "x1"], eps, n, source=NoiseSource("bias"), run=i)
            syn.cells = syn.cells.persist()
            for counts in ("raw", "round_nonneg", "clip_zero"):
                c = sorted(cluster_synopsis(syn, [truth], counts)[0])
                out.append((float(eps), counts, sum((a - b) ** 2 for p, q in zip(c, truth) for a, b in zip(p, q)) / 3))
            syn.cells.unpersist()
    return spark.createDataFrame(out, "eps double, counts string, displacement double").groupBy("eps", "counts").agg(F.avg("displacement").alias("displacement"))


def size_scaling(spark: SparkSession, sf_dirs: list[str], which: str, eps: float, p: Protocol) -> DataFrame:
    """Gaps by the number of rows, beside the predictions."""
    from dpcluster.plans import error_model as em

    out: list[tuple] = []
    for sf in sf_dirs:
        w = WORKLOADS[which]
        df = w.points(spark, sf).persist()
        n, cols = df.count(), w.cols
        base = best_of(df, cols, init_sets(p.inits, w.k, w.d))[1]
        for m in ("noisy_lloyd", "grid_kmeans"):
            sets = [c for _, c in runs(df, cols, w.k, n, eps, m, p)]
            gap = sum(nicv_many(df, cols, sets)) / len(sets) - base
            model = em.mse_noisy_lloyd(n, w.d, w.k, eps, 5) if m == "noisy_lloyd" else em.var_grid_plugged(n, w.d, w.k, eps)
            out.append((n, m, float(gap), float(model)))
        df.unpersist()
    return spark.createDataFrame(out, "n long, method string, gap double, predicted double")


__all__ = ["Protocol", "compare", "grid_spec"]
