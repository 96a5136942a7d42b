"""k-means on a synopsis: any number of starts, no further budget."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger
from dpcluster.operators.centroids import Centroids, init_sets
from dpcluster.operators.grid import GridSpec, Releases, Synopsis, release_grid
from dpcluster.operators.lloyd import Clustering, assign, family_sums, lloyd_many, shift

#: Cells times dimensions up to which the loops run on the driver, in numpy, without a job; both ways give the same centroids.
DRIVER_NUMBERS = 5_000_000
#: Costs that agree to so many digits are equal, and the first start wins.
COST_DIGITS = 9


def synopsis_nicv(cells: DataFrame, cols: list[str], centroids: Centroids) -> float:
    """Weighted mean squared distance of the cells; infinite where the counts add up to nothing."""
    row = assign(cells, cols, centroids).agg(F.sum(F.col("n") * F.col("dist2")).alias("c"), F.sum("n").alias("n")).first()
    return row["c"] / row["n"] if row["n"] and row["n"] > 0 else float("inf")


def lloyd_on_arrays(x: np.ndarray, n: np.ndarray, init: Centroids, max_iter: int = 100, tol: float = 1e-6, r: float = 1.0) -> tuple[Centroids, float, int]:
    """Weighted rounds; negative weights can make them cycle, hence the cap and the clip to the box."""
    c, x2 = np.asarray(init, float), (x * x).sum(1)
    dist = lambda c: x2[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T
    for i in range(max_iter):
        j = dist(c).argmin(1)
        w = np.bincount(j, n, len(c))
        sums = np.column_stack([np.bincount(j, n * x[:, q], len(c)) for q in range(x.shape[1])])
        new = np.clip(np.where(w[:, None] >= 1e-9, sums / np.where(np.abs(w) < 1e-9, 1, w)[:, None], c), -r, r)
        stop = shift(new.tolist(), c.tolist()) < tol
        c = new
        if stop:
            break
    total = n.sum()
    return c.tolist(), float((n * dist(c).min(1)).sum() / total) if total > 0 else float("inf"), i + 1


def cluster_synopsis(synopsis: Synopsis, inits: list[Centroids], counts: str = "raw", max_iter: int = 100, driver_numbers: int | None = None) -> tuple[Centroids, float, int]:
    """The start whose outcome is best on the synopsis itself; a large synopsis stays distributed, and all starts share its scans."""
    cells, spec = synopsis.weighted(counts), synopsis.spec
    if spec.cells * spec.d <= (DRIVER_NUMBERS if driver_numbers is None else driver_numbers):
        got = cells.select("n", *synopsis.cols).toArrow()  # bounded: spec.cells rows
        x, n = np.column_stack([got.column(c).to_numpy() for c in synopsis.cols]), got.column("n").to_numpy().astype(float)
        order = np.lexsort(x.T)
        outcomes = [lloyd_on_arrays(x[order], n[order], c, max_iter, r=spec.r) for c in inits]
        best = min(range(len(inits)), key=lambda i: (round(outcomes[i][1], COST_DIGITS), i))
        return outcomes[best]
    cells = cells.select("n", *synopsis.cols).persist()
    try:
        final, _, scans = lloyd_many(cells, synopsis.cols, inits, max_iter, weight="n", r=spec.r)
        rows = family_sums(cells, synopsis.cols, final, "n").groupBy("run").agg(F.sum("cost").alias("c"), F.sum("n").alias("n")).collect()
    finally:
        cells.unpersist()
    cost = {x["run"]: x["c"] / x["n"] if x["n"] > 0 else float("inf") for x in rows}
    best = min(cost, key=lambda i: (round(cost[i], COST_DIGITS), i))
    return final[best], cost[best], scans


def grid_kmeans(df: DataFrame, cols: list[str], k: int, eps: float, n: float, inits: int | list[Centroids] = 30, counts: str = "raw", source: NoiseSource | None = None, ledger: BudgetLedger | None = None, seed: int = 0, run: int = 0, spec: GridSpec | None = None, max_iter: int = 100, **grid) -> Clustering:
    """One scan of the data; all else reads the synopsis."""
    ledger = ledger or BudgetLedger(eps)
    synopsis = release_grid(df, cols, eps, n, source=source, ledger=ledger, run=run, spec=spec, **grid)
    sets = init_sets(inits, k, len(cols), seed) if isinstance(inits, int) else inits
    c, cost, rounds = cluster_synopsis(synopsis, sets, counts, max_iter)
    return Clustering(c, path="grid", ledger=ledger, stats={"scans": 1, "m": synopsis.spec.m, "capped": synopsis.spec.capped, "synopsis_nicv": cost, "rounds": rounds})


def grid_kmeans_many(df: DataFrame, cols: list[str], eps: float, n: float, sets: list[Centroids], synopses: int, source: NoiseSource | None = None, counts: str = "raw", **grid) -> list[Centroids]:
    """The outcomes of several synopses, for experiments: the data is scanned once for all."""
    with Releases(df, cols, eps, n, source=source, **grid) as releases:
        return [cluster_synopsis(releases.synopsis(i), sets, counts)[0] for i in range(synopses)]


def tune_on_synopsis(synopsis: Synopsis, params, score) -> tuple[object, list]:
    """The parameter with the least score(synopsis, parameter); costs no budget."""
    scores = [(score(synopsis, p), i) for i, p in enumerate(params)]
    return params[min(scores)[1]], [s for s, _ in scores]
