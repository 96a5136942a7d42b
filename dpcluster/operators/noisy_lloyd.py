"""Lloyd rounds with Laplace noise in every count and sum.

In one round a row takes part in one count and d sums of values in [-r, r]: a sensitivity of dr + 1.
With t rounds and equal shares each answer gets noise of scale (dr + 1) t / epsilon.  Noise is added
inside the plan, keyed by run, round, cluster and dimension, before anything reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger, sensitivity
from dpcluster.operators.centroids import Centroids, packed_init, uniform_init
from dpcluster.operators.lloyd import Clustering, assign, family_sums, moved, partial_sums


def shares(eps: float, t: int, schedule="equal") -> list[float]:
    """Budget of each round."""
    if schedule == "equal":
        return [eps / t] * t
    if len(schedule) != t:
        raise ValueError("a schedule needs a weight for each round")
    return [eps * w / sum(schedule) for w in schedule]


def with_empty(sums: DataFrame, k: int, d: int) -> DataFrame:
    """A row for each cluster, also for those without points: they too get noise."""
    every = sums.sparkSession.range(k).select(F.col("id").cast("int").alias("cluster"))
    return every.join(sums, "cluster", "left").select("cluster", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in ["n", *(f"s{i}" for i in range(d))]))


def noise_step(run: int, round_: int, scale: float) -> str:
    """Noise of one run and round is never drawn again at another scale."""
    return f"lloyd-{run}-{round_}-{scale:.9g}"


def noisy_sums(sums: DataFrame, d: int, scale: float, source: NoiseSource, round_: int, run: int = 0) -> DataFrame:
    step = noise_step(run, round_, scale)
    return sums.select("cluster", *((F.col(c) + source.laplace(scale, f"{step}-{c}", "cluster")).alias(c) for c in ["n", *(f"s{i}" for i in range(d))]))


def noisy_lloyd(df: DataFrame, cols: list[str], k: int, eps: float, t: int = 5, r: float = 1.0, init="packed", schedule="equal", source: NoiseSource | None = None, ledger: BudgetLedger | None = None, run: int = 0, seed: int = 0, noise: bool = True) -> Clustering:
    """t scans.  init: packed, uniform, or centroids."""
    source, ledger, d = source or NoiseSource.secret(), ledger or BudgetLedger(eps), len(cols)
    c: Centroids = packed_init(k, d, seed, r)[0] if init == "packed" else uniform_init(k, d, str(seed), r) if init == "uniform" else init
    sens, trace, sizes = sensitivity.centroid_update(d, r), [c], None
    for i, share in enumerate(shares(eps, t, schedule)):
        ledger.spend(f"round {i + 1}", share, sens, k * (d + 1))
        sums = with_empty(partial_sums(assign(df, cols, c), cols), k, d)
        rows = (noisy_sums(sums, d, sens / share, source, i, run) if noise else sums).orderBy("cluster").collect()
        c, sizes = moved(rows, c, 1.0, r), [x["n"] for x in rows]
        trace.append(c)
    return Clustering(c, sizes, f"noisy_lloyd x{t}", trace, ledger, stats={"scans": t})


def noisy_lloyd_many(df: DataFrame, cols: list[str], inits: list[Centroids], noises: int, eps: float, t: int = 5, r: float = 1.0, source: NoiseSource | None = None) -> list[Centroids]:
    """Every init with so many noises, for experiments: t scans for all of them."""
    source = source or NoiseSource()
    sets, d = [c for c in inits for _ in range(noises)], len(cols)
    scale = sensitivity.centroid_update(d, r) * t / eps
    for i in range(t):
        sums = family_sums(df, cols, sets)
        noisy = sums.select("run", "cluster", *((F.col(c) + source.laplace(scale, f"many-{i}-{scale:.9g}-{c}", "run", "cluster")).alias(c) for c in ["n", *(f"s{q}" for q in range(d))]))
        by: dict[int, list] = {}
        for row in noisy.collect():  # runs x k rows
            by.setdefault(row["run"], []).append(row)
        sets = [moved(by.get(j, []), s, 1.0, r) for j, s in enumerate(sets)]
    return sets
