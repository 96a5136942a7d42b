"""Closed forms of the errors, and the threshold at which a refining round pays.

n rows, d dimensions, k clusters, budget eps, t rounds, box [-r, r]; rho is the mean of a
centroid coordinate's size over 2r, 0 to 0.5.
"""

from __future__ import annotations

import math

from dpcluster.operators.grid import THETA, cells_general

RHO = 0.25


def range_var(alpha: float, cells: float, eps: float) -> float:
    """Variance of a range count that covers a share alpha of the cells."""
    return alpha * 2 * cells / eps**2


def range_bias2(beta: float, cells: float, n: float, d: int) -> float:
    return 2 * d * (beta * n / cells ** (1 / d)) ** 2


def range_mse(alpha: float, beta: float, cells: float, n: float, d: int, eps: float) -> float:
    return range_var(alpha, cells, eps) + range_bias2(beta, cells, n, d)


def centroid_mse_delta(s: float, c: float, var_s: float, var_c: float) -> float:
    """First-order error of a noisy sum over a noisy count."""
    return var_s / c**2 + s * s * var_c / c**4


def mse_noisy_lloyd(n: float, d: int, k: int, eps: float, t: int, r: float = 1.0, rho: float = RHO) -> float:
    return 2 * d * (1 + (2 * rho * r) ** 2) * (k * t * (d * r + 1) / (n * eps)) ** 2


def mse_two_stage(n: float, d: int, k: int, eps: float, r: float = 1.0, rho: float = RHO) -> float:
    """One round on half the budget."""
    return mse_noisy_lloyd(n, d, k, eps / 2, 1, r, rho)


def var_grid(n: float, d: int, k: int, eps: float, cells: float, r: float = 1.0) -> float:
    """Variance of centroids from a synopsis of equal cube-shaped clusters."""
    return 2 * d * cells * r * r * k ** ((d - 2) / d) / (3 * n * n * eps * eps)


def var_grid_plugged(n: float, d: int, k: int, eps: float, r: float = 1.0, theta: float = THETA) -> float:
    return var_grid(n, d, k, eps, cells_general(n, eps, d, theta), r)


def bias2_grid_bound(d: int, cells: float, r: float = 1.0) -> float:
    return d * r * r / cells ** (2 / d)


def epsilon_threshold(n: float, d: int, k: int, r: float = 1.0, rho: float = RHO, theta: float = THETA) -> float:
    """From this budget on, a round on half of it errs less than the synopsis on all of it.

    mse_two_stage = X / eps^2 and var_grid_plugged = Y / eps^(4 / (2 + d)); they meet at (X / Y)^((2 + d) / (2 d))."""
    x = mse_two_stage(n, d, k, 1.0, r, rho)
    y = var_grid_plugged(n, d, k, 1.0, r, theta)
    return (x / y) ** ((2 + d) / (2 * d))


def epsilon_threshold_sql(n="n", d="d", k="k", rho="rho", theta: float = THETA) -> str:
    """With r = 1, over a table of parameters."""
    x = f"(2.0 * {d} * (1 + pow(2.0 * {rho}, 2)) * pow(2.0 * {k} * ({d} + 1.0) / {n}, 2))"
    y = f"(2.0 * {d} * pow({n} / {theta}, 2.0 * {d} / (2.0 + {d})) * pow({k}, ({d} - 2.0) / {d}) / (3.0 * {n} * {n}))"
    return f"pow({x} / {y}, (2.0 + {d}) / (2.0 * {d}))"


def beats_noisy_lloyd(t: int) -> bool:
    """One round on half the budget against t rounds on all of it."""
    return t >= 2


def evolve_rounds(n: float, eps: float, x: float = 1.25e-3, keep: int = 10, floor: int = 8) -> int:
    return max(floor, int(math.floor(x * n * eps / keep)))


def evolve_share(eps: float, rounds: int, keep: int = 10) -> float:
    return eps / (rounds * keep)


def block_count(n: float, rule="power", exponent: float = 0.4, k: int = 1) -> int:
    """power: n^exponent blocks; 3k: blocks of 3k rows; ("size_exp", a): blocks of n^a rows."""
    if rule == "power":
        blocks = n**exponent
    elif rule == "3k":
        blocks = n / (3 * k)
    else:
        blocks = n / n ** rule[1]
    return max(1, math.floor(blocks + 0.5))
