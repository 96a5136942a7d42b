"""The planner: a synopsis on half the budget and one noisy round on the rest, where that pays."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame

from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger
from dpcluster.operators.centroids import Centroids, init_sets
from dpcluster.operators.grid import THETA, GridSpec, cells_general, grid_spec
from dpcluster.operators.grid_kmeans import grid_kmeans, grid_kmeans_many
from dpcluster.operators.lloyd import Clustering
from dpcluster.operators.noisy_lloyd import noisy_lloyd, noisy_lloyd_many
from dpcluster.plans import error_model as em


@dataclass(frozen=True)
class Decision:
    """What the planner saw and chose."""

    eps: float
    eps_star: float
    t: int
    mse_noisy: float
    var_grid: float
    mse_refine: float
    path: str
    reason: str

    def explain(self) -> str:
        return f"{self.path}: {self.reason} (epsilon {self.eps:g}, threshold {self.eps_star:.4g}; predicted errors: {self.t} noisy rounds {self.mse_noisy:.3g}, synopsis {self.var_grid:.3g}, refined {self.mse_refine:.3g})"


def decide(n: float, d: int, k: int, eps: float, t: int = 5, r: float = 1.0, rho: float = em.RHO, theta: float = THETA, max_cells: int | None = None, include_bias: bool = False, force: str | None = None) -> Decision:
    """Refine if the budget reaches the threshold and a noisy run would take two rounds or more.

    With a cap on cells the variance is that of the capped grid, and so is the comparison."""
    cells = cells_general(n, eps, d, theta)
    spec = grid_spec(cells, d, r, max_cells=max_cells) if max_cells else None
    capped = bool(spec and spec.capped)
    used = float(spec.cells) if capped else cells
    var = em.var_grid(n, d, k, eps, used, r) + (em.bias2_grid_bound(d, used, r) if include_bias or capped else 0.0)
    refine, star = em.mse_two_stage(n, d, k, eps, r, rho), em.epsilon_threshold(n, d, k, r, rho, theta)
    pays = refine <= var if include_bias or capped else eps >= star
    if force:
        path, why = {"refine": ("grid+refine", "forced"), "grid": ("grid", "forced")}[force]
    elif not em.beats_noisy_lloyd(t):
        path, why = "grid", "a single noisy round is as good as a refined one"
    else:
        path, why = ("grid+refine", "a refining round errs less than the synopsis") if pays else ("grid", "the budget is too small for a refining round")
    return Decision(eps, star, t, em.mse_noisy_lloyd(n, d, k, eps, t, r, rho), var, refine, path, why)


def two_stage(df: DataFrame, cols: list[str], k: int, eps: float, n: float, rho: float = em.RHO, split: float = 0.5, refine_rounds: int = 1, t: int = 5, force: str | None = None, inits: int | list[Centroids] = 30, source: NoiseSource | None = None, seed: int = 0, theta: float = THETA, max_cells: int | None = None, include_bias: bool = False, run: int = 0, max_iter: int = 100, spec: GridSpec | None = None) -> Clustering:
    """Without refinement exactly grid_kmeans on the whole budget; with it, grid on split * eps, then noisy rounds on the rest."""
    source, ledger = source or NoiseSource.secret(), BudgetLedger(eps)
    choice = decide(n, len(cols), k, eps, t, rho=rho, theta=theta, max_cells=max_cells, include_bias=include_bias, force=force)
    first = eps if choice.path == "grid" else split * eps
    out = grid_kmeans(df, cols, k, first, n, inits, source=source, ledger=ledger, seed=seed, run=run, theta=theta, max_cells=max_cells, max_iter=max_iter, spec=spec)
    if choice.path == "grid+refine":
        scans = out.stats["scans"] + refine_rounds
        out = noisy_lloyd(df, cols, k, eps - first, refine_rounds, init=out.centroids, source=source, ledger=ledger, run=run)
        out.stats = {"scans": scans}
    out.path, out.decision = choice.path, choice
    return out


def two_stage_many(df: DataFrame, cols: list[str], k: int, eps: float, n: float, first: int = 10, second: int = 10, source: NoiseSource | None = None, inits: int = 30, seed: int = 0, force: str | None = None, max_cells: int | None = None) -> list[Centroids]:
    """Repetitions for experiments: one scan for all first stages, and one for all refinements."""
    source = source or NoiseSource()
    choice = decide(n, len(cols), k, eps, max_cells=max_cells, force=force)
    share = eps if choice.path == "grid" else eps / 2
    sets = init_sets(inits, k, len(cols), seed)
    starts = grid_kmeans_many(df, cols, share, n, sets, first, source, max_cells=max_cells)
    return starts if choice.path == "grid" else noisy_lloyd_many(df, cols, starts, second, eps - share, 1, source=source)


def is_identity(n: float, d: int, k: int, eps: float) -> bool:
    return decide(n, d, k, eps).path == "grid" and math.isfinite(eps)
