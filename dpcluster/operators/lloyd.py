"""Assignment and centroid updates, without noise.

Centroids are literals of the plan while they are few, so a round is one scan inside generated
code and a shuffle of at most partitions x clusters rows.  Families of runs advance together: one
scan of Arrow batches gives the partial sums of all of them.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpcluster.operators.centroids import Centroids, as_table, uniform_init
from dpcluster.operators.point_trees import summed

#: Above so many numbers the generated code outgrows what the JIT compiles.
MAX_LITERALS = 400


def distance2(cols: list[str], c: list[float]) -> Column:
    total = (F.col(cols[0]) - float(c[0])) * (F.col(cols[0]) - float(c[0]))
    for x, v in zip(cols[1:], c[1:]):
        total = total + (F.col(x) - float(v)) * (F.col(x) - float(v))
    return total


def nearest(cols: list[str], centroids: Centroids) -> Column:
    """struct(dist2, j) of the nearest centroid; the lower number wins a tie."""
    return F.array_min(F.array(*(F.struct(distance2(cols, c).alias("dist2"), F.lit(j).alias("j")) for j, c in enumerate(centroids))))


def assign(df: DataFrame, cols: list[str], centroids: Centroids, method: str = "auto") -> DataFrame:
    """Adds cluster and dist2.  method: expr (literals), broadcast (join), arrow, or auto by size."""
    if method == "auto":
        method = "expr" if len(cols) * len(centroids) <= MAX_LITERALS else "arrow"
    if method == "expr":
        return df.withColumn("__n", nearest(cols, centroids)).withColumns({"cluster": F.col("__n.j"), "dist2": F.col("__n.dist2")}).drop("__n")
    if method == "broadcast":  # k rows; a row meets them all, which is what assignment means
        small = as_table(df.sparkSession, [centroids]).groupBy("run").agg(F.collect_list(F.struct("j", "c")).alias("cs")).select("cs")
        point = F.array(*map(F.col, cols))
        dist = lambda c: F.aggregate(F.zip_with(point, c["c"], lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
        return df.join(F.broadcast(small)).withColumn("__n", F.array_min(F.transform("cs", lambda c: F.struct(dist(c).alias("dist2"), c["j"].alias("j"))))).withColumns({"cluster": F.col("__n.j"), "dist2": F.col("__n.dist2")}).drop("__n", "cs")
    c = np.asarray(centroids, float)

    def run(batches):
        for batch in batches:
            x = np.column_stack([batch.column(n).to_numpy(zero_copy_only=False) for n in cols]) if batch.num_rows else np.zeros((0, len(cols)))
            d = ((x[:, None, :] - c[None]) ** 2).sum(2)
            j = d.argmin(1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(j.astype(np.int32)), pa.array(d[np.arange(len(j)), j])], names=[*batch.schema.names, "cluster", "dist2"])

    types = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    return df.mapInArrow(run, f"{types}, cluster int, dist2 double")


def partial_sums(assigned: DataFrame, cols: list[str], weight: str | None = None) -> DataFrame:
    """Per cluster: n and the sums s0.. of the coordinates, with weights if given."""
    w = F.col(weight) if weight else F.lit(1.0)
    return assigned.groupBy("cluster").agg(F.sum(w).alias("n"), *(F.sum(w * F.col(x)).alias(f"s{i}") for i, x in enumerate(cols)))


def moved(sums: list, centroids: Centroids, min_count: float = 1.0, r: float | None = None, reseed: Centroids | None = None) -> Centroids:
    """Next centroids from rows of sums; a cluster whose count is below min_count keeps its centroid, or takes that of ``reseed``."""
    out = [list(c) for c in reseed or centroids]
    for row in sums:
        if row["n"] is not None and row["n"] >= min_count:
            out[row["cluster"]] = [row[f"s{i}"] / row["n"] for i in range(len(out[0]))]
    return [[min(r, max(-r, x)) for x in c] for c in out] if r else out


def shift(a: Centroids, b: Centroids) -> float:
    return max(sum((x - y) ** 2 for x, y in zip(p, q)) ** 0.5 for p, q in zip(a, b))


@dataclass
class Clustering:
    """Centroids and how they came about.  Of its parts only centroids and noisy sizes are private outputs."""

    centroids: Centroids
    sizes: list[float] | None = None
    path: str = ""
    trace: list | None = None
    ledger: object = None
    decision: object = None
    stats: dict | None = None

    def to_df(self, spark) -> DataFrame:
        return as_table(spark, [self.centroids]).drop("run")


def lloyd(df: DataFrame, cols: list[str], init: Centroids, max_iter: int = 100, tol: float = 1e-6, weight: str | None = None, r: float | None = None, on_empty: str = "keep", seed: str = "reseed") -> Clustering:
    """One job a round, k rows to the driver; stops when no centroid moves by more than tol.

    on_empty: a cluster without points keeps its centroid, or with "reseed" gets a keyed uniform one."""
    c, trace = init, [init]
    min_count = 1.0 if weight is None else 1e-9
    for i in range(max_iter):
        fresh = uniform_init(len(c), len(cols), f"{seed}-{i}", r or 1.0) if on_empty == "reseed" else None
        new = moved(partial_sums(assign(df, cols, c), cols, weight).collect(), c, min_count, r, fresh)
        trace.append(new)
        stop, c = shift(new, c) < tol, new
        if stop:
            break
    return Clustering(c, path="lloyd", trace=trace, stats={"scans": len(trace) - 1})


def grouped(df: DataFrame, cols: list[str], weight: str) -> DataFrame:
    """Each distinct point once, with the number of its rows as weight."""
    return df.groupBy(*cols).agg(F.count("*").cast("double").alias(weight))


def _add_sums(total: np.ndarray, cs: np.ndarray, full: np.ndarray, ws: np.ndarray) -> None:
    """Adds what points and weights give to (run, cluster): weight, weighted sums, cost."""
    k, d = cs.shape[1:]
    for at in range(0, len(full), 8192):
        x, w = full[at : at + 8192], ws[at : at + 8192]
        x2 = (x * x).sum(1)
        for i, c in enumerate(cs):
            dist = x2[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T
            j = dist.argmin(1)
            total[i, :, 0] += np.bincount(j, w, k)
            for q in range(d):
                total[i, :, 1 + q] += np.bincount(j, w * x[:, q], k)
            total[i, :, -1] += np.bincount(j, w * np.maximum(dist[np.arange(len(j)), j], 0), k)


def point_blocks(df: DataFrame, cols: list[str], weight: str | None = None) -> RDD:
    """The points of each Arrow batch and their weights, as bytes: for rounds that read them again and again."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                full = np.column_stack([*(batch.column(n).to_numpy(zero_copy_only=False) for n in cols), batch.column(weight).to_numpy(zero_copy_only=False) if weight else np.ones(batch.num_rows)])
                yield pa.RecordBatch.from_arrays([pa.array([full.astype(float).tobytes()], pa.binary())], names=["points"])

    tasks = 2 * df.sparkSession.sparkContext.defaultParallelism  # more only cost time in each round
    return df.select(*cols, *([weight] if weight else [])).coalesce(tasks).mapInArrow(run, "points binary").rdd.map(lambda row: row[0])


def block_sums(blocks: RDD, d: int, sets: list[Centroids]) -> np.ndarray:
    """What ``family_sums`` gives, as an array (run, cluster, n and sums and cost): one job without a shuffle on up to 64 partitions."""
    cs = np.asarray(sets, float)

    def run(rows):
        total = np.zeros((*cs.shape[:2], d + 2))
        for row in rows:
            full = np.frombuffer(row).reshape(-1, d + 1)
            _add_sums(total, cs, full[:, :-1], full[:, -1])
        yield total

    return summed(blocks.mapPartitions(run))


def family_sums(df: DataFrame, cols: list[str], sets: list[Centroids], weight: str | None = None) -> DataFrame:
    """(run, cluster, n, s0.., cost) of many centroid sets in one scan."""
    cs, d = np.asarray(sets, float), len(cols)
    k = cs.shape[1]
    fields = ["run", "cluster", "n", *(f"s{i}" for i in range(d)), "cost"]

    def run(batches):
        total = np.zeros((len(cs), k, d + 2))
        for batch in batches:
            if batch.num_rows:
                full = np.column_stack([batch.column(n).to_numpy(zero_copy_only=False) for n in cols])
                _add_sums(total, cs, full, batch.column(weight).to_numpy(zero_copy_only=False) if weight else np.ones(len(full)))
        i, j = np.divmod(np.arange(len(cs) * k), k)
        flat = total.reshape(-1, d + 2)
        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j.astype(np.int32)), *(pa.array(flat[:, q]) for q in range(d + 2))], names=fields)

    schema = "run long, cluster int, n double, " + ", ".join(f"s{i} double" for i in range(d)) + ", cost double"
    parts = df.select(*cols, *([weight] if weight else [])).mapInArrow(run, schema)
    return parts.groupBy("run", "cluster").agg(*(F.sum(c).alias(c) for c in fields[2:]))


def family_step(sums: list, sets: list[Centroids], min_count: float = 1.0, r: float | None = None) -> list[Centroids]:
    by: dict[int, list] = {}
    for row in sums:
        by.setdefault(row["run"], []).append(row)
    return [moved(by.get(i, []), s, min_count, r) for i, s in enumerate(sets)]


def lloyd_many(df: DataFrame, cols: list[str], sets: list[Centroids], max_iter: int = 100, tol: float = 1e-6, weight: str | None = None, r: float | None = None) -> tuple[list[Centroids], list[list[float]], int]:
    """All runs advance in each scan.  Gives final sets, the cost of each set before each round, and the scans."""
    costs, scans, fields = [[] for _ in sets], 0, ["n", *(f"s{i}" for i in range(len(cols)))]
    blocks = point_blocks(df, cols, weight).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        for _ in range(max_iter):
            total = block_sums(blocks, len(cols), sets)  # runs x k rows
            scans += 1
            for i, mine in enumerate(total):
                n = mine[:, 0].sum()
                costs[i].append(float(mine[:, -1].sum() / n) if n > 0 else float("inf"))
            rows = [{"run": i, "cluster": j} | dict(zip(fields, map(float, v))) for i, mine in enumerate(total) for j, v in enumerate(mine)]
            new = family_step(rows, sets, 1.0 if weight is None else 1e-9, r)
            stop, sets = all(shift(a, b) < tol for a, b in zip(new, sets)), new
            if stop:
                break
    finally:
        blocks.unpersist()
    return sets, costs, scans


def best_of(df: DataFrame, cols: list[str], sets: list[Centroids], **options) -> tuple[Centroids, float]:
    """The non-private baseline: the run with the least cost."""
    final, _, _ = lloyd_many(df, cols, sets, **options)
    costs = {r["run"]: r["v"] for r in family_sums(df, cols, final, options.get("weight")).groupBy("run").agg((F.sum("cost") / F.sum("n")).alias("v")).collect()}
    run = min(costs, key=lambda i: (costs[i], i))
    return final[run], costs[run]


def nicv(df: DataFrame, cols: list[str], centroids: Centroids) -> float:
    """Mean squared distance to the nearest centroid; for evaluation, not a private output."""
    return assign(df, cols, centroids).agg(F.avg("dist2")).first()[0]


def nicv_many(df: DataFrame, cols: list[str], sets: list[Centroids]) -> list[float]:
    got = {r["run"]: r["v"] for r in family_sums(df, cols, sets).groupBy("run").agg((F.sum("cost") / F.sum("n")).alias("v")).collect()}
    return [got[i] for i in range(len(sets))]
