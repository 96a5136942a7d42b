"""Model fitting by private evolution: selection by the exponential mechanism, crossover, mutation.

The pool is a few hundred vectors; the fitness of all of them, and of the pools of other runs, is one job a round
over points that are read once.  Picks and children are numbers of the driver, from the same keyed draws as in Spark.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger, sensitivity
from dpcluster.operators.lloyd import Clustering, family_sums
from dpcluster.operators.point_trees import point_trees, tree_costs
from dpcluster.plans.error_model import evolve_rounds, evolve_share

POOL, KEEP = 200, 10


def crossover(a: Column, b: Column, cut: Column, n: int) -> tuple[Column, Column]:
    """Tails swap behind the cut."""
    rest = F.lit(n) - cut
    return F.concat(F.slice(a, 1, cut), F.slice(b, cut + 1, rest)), F.concat(F.slice(b, 1, cut), F.slice(a, cut + 1, rest))


def mutate(theta: Column, pos: Column, delta: Column, r: float = 1.0) -> Column:
    """One coordinate moves, within the box."""
    return F.transform(theta, lambda v, i: F.when(i == pos, F.greatest(F.lit(-r), F.least(F.lit(r), v + delta))).otherwise(v))


def init_pool(n: int, k: int, d: int, source: NoiseSource, r: float = 1.0) -> np.ndarray:
    return np.array([[(2 * source.draw("pool", i, j) - 1) * r for j in range(k * d)] for i in range(n)])


def fitness_of_pool(df: DataFrame, cols: list[str], pool: np.ndarray, k: int) -> DataFrame:
    """(cand, fit): minus the sum of squared distances to the nearest centroid, all candidates in one scan."""
    sets = pool.reshape(len(pool), k, -1).tolist()
    return family_sums(df, cols, sets).groupBy(F.col("run").alias("cand")).agg((-F.sum("cost")).alias("fit"))


def offspring(parents: DataFrame, m: int, n: int, dim: int, half: float, source: NoiseSource, step: str, r: float = 1.0) -> DataFrame:
    """(run, cand, theta): n children of each run's m parents (run, place, theta), by crossover and mutation.

    Children 2i and 2i + 1 come from one pair of parents and one cut."""
    u = lambda what, of: source.uniform(f"{step}-{what}", "run", of)
    pair = F.floor(F.col("cand") / 2)
    first = F.floor(u("first", pair) * m).cast("int")
    second = F.pmod(first + 1 + F.floor(u("second", pair) * max(1, m - 1)).cast("int"), F.lit(m))  # another parent, where there is one
    cut = (1 + F.floor(u("cut", pair) * max(1, dim - 1))).cast("int")
    made = parents.select("run").distinct().withColumn("cand", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).withColumns({"first": first, "second": second, "cut": cut})
    a, b = (parents.select(F.col("run").alias(f"run_{x}"), F.col("place").alias(f"place_{x}"), F.col("theta").alias(x)) for x in "ab")
    both = made.join(a, (F.col("run") == F.col("run_a")) & (F.col("first") == F.col("place_a"))).join(b, (F.col("run") == F.col("run_b")) & (F.col("second") == F.col("place_b")))
    one, two = crossover(F.col("a"), F.col("b"), F.col("cut"), dim)
    child = F.when(F.col("cand") % 2 == 0, one).otherwise(two) if dim > 1 else F.col("a")
    moved = mutate(F.col("child"), F.floor(u("place", "cand") * dim).cast("int"), (2 * u("move", "cand") - 1) * half, r)
    return both.withColumn("child", child).select("run", "cand", moved.alias("theta"))


def children(parents: list[list[np.ndarray]], n: int, half: float, source: NoiseSource, step: str, r: float = 1.0) -> np.ndarray:
    """What ``offspring`` gives, (runs, n, dim), from each run's parents by place."""
    m, dim, out = len(parents[0]), len(parents[0][0]), []
    for run, mine in enumerate(parents):
        u = lambda what, of: source.draw(f"{step}-{what}", run, of)  # noqa: B023, E731
        for cand in range(n):
            pair = cand // 2
            first = math.floor(u("first", pair) * m)
            second = (first + 1 + math.floor(u("second", pair) * max(1, m - 1))) % m
            a, b = (mine[first], mine[second]) if cand % 2 == 0 or dim == 1 else (mine[second], mine[first])
            cut = 1 + math.floor(u("cut", pair) * max(1, dim - 1))
            child = np.concatenate([a[:cut], b[cut:]])
            at = math.floor(u("place", cand) * dim)
            child[at] = max(-r, min(r, child[at] + (2 * u("move", cand) - 1) * half))
            out.append(child)
    return np.array(out).reshape(len(parents), n, dim)


def evolve_fits(df: DataFrame, fitness, starts: list[np.ndarray], sens: float, eps: float, rounds: int, keep: int = KEEP, private: bool = True, source: NoiseSource | None = None, ledger: BudgetLedger | None = None, traces: list[list] | None = None) -> list[np.ndarray]:
    """Several runs, whose pools are judged in the same scans.  fitness(df, pool) -> (cand, fit) or the fits in order, larger is better.

    A round costs keep picks; the last makes one, with their whole share."""
    source, size = source or NoiseSource.secret(), len(starts[0])
    dim, pools = starts[0].shape[1], np.stack(starts)
    for g in range(rounds):
        last = g == rounds - 1
        n, share = (1, eps / rounds) if last else (keep, evolve_share(eps, rounds, keep))
        fits: list[list] = [[] for _ in starts]
        got = fitness(df, pools.reshape(-1, dim))
        for cand, fit in ((x["cand"], x["fit"]) for x in got.select("cand", "fit").collect()) if isinstance(got, DataFrame) else enumerate(map(float, got)):  # runs x pool rows
            fits[cand // size].append((cand % size, fit))
        if private and ledger:
            ledger.spend(f"generation {g + 1}", n * share, sens, n)
        step, chosen = f"generation-{g}-{eps:.9g}", []
        for run, scores in enumerate(fits):
            rank = {cand: fit * (share / (2 * sens)) - math.log(-math.log(source.draw(step, run, cand))) if private else fit for cand, fit in scores}
            picked = sorted(scores, key=lambda x: (-rank[x[0]], x[0]))[:n]  # noqa: B023
            chosen.append([pools[run, cand] for cand, _ in picked])
            if traces is not None:
                traces[run].append(-max(fit for _, fit in picked))
        if last:
            return [mine[0] for mine in chosen]
        pools = children(chosen, size, 0.5**g, source, f"children-{g}-{eps:.9g}")


def evolve_fit(df: DataFrame, fitness, start: np.ndarray, sens: float, eps: float, rounds: int, **options) -> np.ndarray:
    """One run, for any model whose fitness is bounded."""
    return evolve_fits(df, fitness, [start], sens, eps, rounds, **options)[0]


def evolve_many(df: DataFrame, cols: list[str], k: int, eps: float, n: float, runs: int, pool: int = POOL, keep: int = KEEP, rounds: int | None = None, private: bool = True, source: NoiseSource | None = None, seed: int = 0, weight: str | None = None) -> list[Clustering]:
    """Repetitions for experiments: one job a round for all of them.  Each run pays the whole budget.

    weight: how many equal points a row stands for."""
    d, ledger, traces = len(cols), BudgetLedger(eps), [[] for _ in range(runs)]
    rounds = rounds or evolve_rounds(n, eps, keep=keep)
    starts = [init_pool(pool, k, d, NoiseSource(f"pool-{seed + i}")) for i in range(runs)]
    trees = point_trees(df, cols, weight).persist(StorageLevel.MEMORY_AND_DISK)
    judge = lambda t, p: -tree_costs(t, p.reshape(len(p), k, d))
    try:
        found = evolve_fits(trees, judge, starts, sensitivity.fitness(d), eps, rounds, keep, private, source, ledger if private else None, traces)
    finally:
        trees.unpersist()
    return [Clustering(x.reshape(k, d).tolist(), path=f"evolve x{rounds}", trace=t, ledger=ledger, stats={"scans": rounds}) for x, t in zip(found, traces)]


def evolve(df: DataFrame, cols: list[str], k: int, eps: float, n: float, **options) -> Clustering:
    return evolve_many(df, cols, k, eps, n, 1, **options)[0]
