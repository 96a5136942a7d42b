"""Sample and aggregate: disjoint blocks, any function of a block, a private average.

Rows go to blocks by a keyed hash.  Blocks are dealt to as many tasks as the cluster likes, and are
worked on inside a task in their order, so a block is a few rows of a stream and not a task of its
own; what a task sends on is one partial sum.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger, private_range
from dpcluster.operators.centroids import Centroids, packed_init
from dpcluster.operators.lloyd import Clustering
from dpcluster.plans.error_model import block_count


def with_block(df: DataFrame, blocks: int, source: NoiseSource, key: str | None = None) -> DataFrame:
    """A block for each row, from the row's key, or else from its place in the input; never from its values, which may be frequent."""
    return df.withColumn("block", F.floor(source.uniform("block", F.col(key) if key else F.monotonically_increasing_id()) * blocks).cast("long"))


def block_start(x: np.ndarray, k: int, source: NoiseSource, block: int) -> np.ndarray:
    """Starts of a block's own: rows of it, drawn by keyed numbers from the rows in the order of their values."""
    rows = np.lexsort(x.T[::-1])
    return x[rows[[int(source.draw("block-start", block, j) * len(x)) for j in range(k)]]]


def lloyd_block(x: np.ndarray, init: np.ndarray, max_iter: int = 300) -> np.ndarray:
    """Rounds until nothing moves."""
    c = init.copy()
    for _ in range(max_iter):
        j = ((x[:, None, :] - c[None]) ** 2).sum(2).argmin(1)
        n = np.bincount(j, minlength=len(c))
        sums = np.column_stack([np.bincount(j, x[:, q], len(c)) for q in range(x.shape[1])])
        new = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
        stop, c = np.abs(new - c).max() < 1e-6, new
        if stop:
            break
    return c


def align(c: np.ndarray, how: str, anchor: np.ndarray) -> np.ndarray:
    """Which centroid of a block is the j-th: by first coordinates, or the nearest to an anchor, or as they come."""
    if how == "lexicographic":
        return c[np.lexsort(c.T[::-1])]
    if how == "anchor":
        left, order = list(range(len(c))), []
        for a in anchor:
            best = min(left, key=lambda i: ((c[i] - a) ** 2).sum())
            left.remove(best)
            order.append(best)
        return c[order]
    return c


def sample_aggregate(df: DataFrame, cols: list[str], fn, blocks: int, lo: list[float], hi: list[float], eps: float | None, source: NoiseSource, key: str | None = None, ledger: BudgetLedger | None = None, run: int = 0) -> list[float]:
    """The noisy average of fn(points of a block, number of the block), a vector; each value is clamped to [lo, hi] before.

    Noise for each of D outputs has the scale (hi - lo) * D / (blocks * eps); without eps there is none."""
    dim, low, high = len(lo), np.asarray(lo, float), np.asarray(hi, float)

    def partial(batches):
        total, count, held, name = np.zeros(dim), 0, [], None

        def close():
            nonlocal total, count
            total = total + np.clip(np.asarray(fn(np.concatenate(held), name), float), low, high)
            count += 1

        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.column_stack([batch.column(c).to_numpy(zero_copy_only=False) for c in cols])
            b = batch.column("block").to_numpy()
            cuts = np.flatnonzero(np.diff(b)) + 1
            for part, block in zip(np.split(x, cuts), b[np.concatenate([[0], cuts])]):
                if name is not None and block != name:
                    close()
                    held = []
                name = block
                held.append(part)
        if held:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([count], pa.int64()), pa.array([total.tolist()], pa.list_(pa.float64()))], names=["blocks", "total"])

    placed = with_block(df, blocks, source, key).select("block", *cols)
    parts = placed.repartition("block").sortWithinPartitions("block").mapInArrow(partial, "blocks long, total array<double>")
    sums = parts.select("blocks", F.posexplode("total").alias("i", "v")).groupBy("i").agg(F.sum("v").alias("v"), F.sum("blocks").alias("b"))
    got = {r["i"]: (r["v"], r["b"]) for r in sums.collect()}
    seen = got[0][1] if got else 0
    empty = np.clip((low + high) / 2, low, high) * (blocks - seen)  # a block without rows answers with the middle
    mean = [(got.get(i, (0.0, 0))[0] + empty[i]) / blocks for i in range(dim)]
    if eps is None:
        return mean
    if ledger:
        ledger.parallel("block average", eps, blocks)
    return [m + _laplace(source, (h - l) * dim / (blocks * eps), noise_step(run, eps), blocks, i) for i, (m, l, h) in enumerate(zip(mean, lo, hi))]


def noise_step(run: int, eps: float) -> str:
    """Noise of one run, budget and number of blocks is never drawn again for others."""
    return f"block-average-{run}-{eps:.9g}"


def _laplace(source: NoiseSource, scale: float, step: str, blocks: int, i: int) -> float:
    u = source.draw(step, blocks, i) - 0.5
    return float(-scale * np.sign(u) * np.log(1 - 2 * abs(u)))


def noise_scale(width: float, k: int, d: int, blocks: int, eps: float) -> float:
    """Half the budget is for the range, the other for all k * d coordinates."""
    return 2 * width * k * d / (blocks * eps)


def block_average(df: DataFrame, cols: list[str], k: int, eps: float, n: int, blocks="power", exponent: float = 0.4, clip_range: bool = True, noise: bool = True, alignment: str = "lexicographic", source: NoiseSource | None = None, seed: int = 0, key: str | None = None, r: float = 1.0, max_iter: int = 300, range_bins: int = 1024) -> Clustering:
    """blocks: power (n^exponent), 3k, ("size_exp", a), or a number.  seed: the number of the run."""
    source, ledger, d = source or NoiseSource.secret(), BudgetLedger(eps), len(cols)
    ell = blocks if isinstance(blocks, int) else block_count(n, blocks, exponent, k)
    init = np.asarray(packed_init(k, d, seed, r)[0])
    if noise:
        rows = {x["dim"]: (x["lo"], x["hi"]) for x in private_range(df, cols, -r, r, eps / 2, n, source, clip=clip_range, bins=range_bins).collect()}
        ledger.spend("output range", eps / 2, 1.0, 2 * d)
    else:
        rows = {i: (-r, r) for i in range(d)}
    lo, hi = [rows[i][0] for _ in range(k) for i in range(d)], [rows[i][1] for _ in range(k) for i in range(d)]

    def fn(x: np.ndarray, block: int) -> np.ndarray:
        if len(x) < k:
            return np.tile([(rows[i][0] + rows[i][1]) / 2 for i in range(d)], k)
        return align(lloyd_block(x, block_start(x, k, source, block), max_iter), alignment, init).ravel()

    flat = sample_aggregate(df, cols, fn, ell, lo, hi, eps / 2 if noise else None, source, key, ledger, seed)
    c = np.asarray(flat).reshape(k, d)
    return Clustering((np.clip(c, -r, r) if clip_range else c).tolist(), path=f"block_average {ell}", ledger=ledger, stats={"blocks": ell, "scans": 2 if noise else 1, "lo": lo[:d], "hi": hi[:d]})


def noise_only(best: Centroids, width: list[float], ell: int, eps: float, source: NoiseSource, r: float = 1.0) -> Centroids:
    """The best known centroids with the noise of the method: what noise alone costs."""
    k, d = len(best), len(best[0])
    out = [[x + _laplace(source, noise_scale(width[i], k, d, ell, eps), "noise-only", ell, j * d + i) for i, x in enumerate(c)] for j, c in enumerate(best)]
    return [[min(r, max(-r, x)) for x in c] for c in out]


def block_error_sources(df: DataFrame, cols: list[str], k: int, eps: float, n: int, best: Centroids, exponents, source: NoiseSource, evaluate) -> list[tuple[float, int, float, float, float]]:
    """(exponent, blocks, total, aggregation alone, noise alone) by the exponent of the block size."""
    out = []
    for a in exponents:
        ell = block_count(n, ("size_exp", a))
        whole = block_average(df, cols, k, eps, n, ell, source=source).centroids
        bare = block_average(df, cols, k, eps, n, ell, noise=False, source=source).centroids
        out.append((a, ell, evaluate(whole), evaluate(bare), evaluate(noise_only(best, [2.0] * len(cols), ell, eps, source))))
    return out


def pairs(n: int):
    return itertools.combinations(range(n), 2)
