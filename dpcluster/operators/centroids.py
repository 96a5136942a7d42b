"""Initial centroids that need no data, and so no budget."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from dpcluster.functions.noise import NoiseSource

Centroids = list[list[float]]


def uniform_init(k: int, d: int, seed: str = "uniform", r: float = 1.0) -> Centroids:
    """k points uniform in the box, from keyed numbers (so SQL can make them too)."""
    src = NoiseSource(seed)
    return [[(2 * src.draw("init", j, i) - 1) * r for i in range(d)] for j in range(k)]


def _place(k: int, d: int, a: float, rng: np.random.Generator, tries: int, r: float) -> np.ndarray | None:
    out = np.empty((0, d))
    for _ in range(k):
        for x in rng.uniform(-(r - a), r - a, (tries, d)):
            if not len(out) or ((out - x) ** 2).sum(1).min() >= 4 * a * a:
                out = np.vstack([out, x])
                break
        else:
            return None
    return out


def packed_init(k: int, d: int, seed: int = 0, r: float = 1.0, tries: int = 300, rounds: int = 20) -> tuple[Centroids, float]:
    """Centroids a away from each wall and 2a from each other, for the largest a that a bisection finds."""
    rng, lo, hi = np.random.default_rng(seed), 0.0, r
    best = rng.uniform(-r, r, (k, d))
    for _ in range(rounds):
        a = (lo + hi) / 2
        got = _place(k, d, a, rng, tries, r)
        if got is None:
            hi = a
        else:
            lo, best = a, got
    return best.tolist(), lo


def init_sets(n: int, k: int, d: int, seed: int = 0, kind: str = "packed", r: float = 1.0) -> list[Centroids]:
    return [packed_init(k, d, seed + i, r, tries=100, rounds=12)[0] if kind == "packed" else uniform_init(k, d, f"{seed + i}", r) for i in range(n)]


def as_table(spark: SparkSession, sets: list[Centroids], name: str = "run") -> DataFrame:
    rows = [(i, j, [float(x) for x in c]) for i, s in enumerate(sets) for j, c in enumerate(s)]
    return spark.createDataFrame(rows, f"{name} long, j int, c array<double>")
