"""Public boxes and the map of attributes to [-r, r]."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Domain:
    """Columns and their public bounds; never taken from the rows."""

    columns: tuple[str, ...]
    lo: tuple[float, ...]
    hi: tuple[float, ...]
    r: float = 1.0

    def __post_init__(self):
        if not len(self.columns) == len(self.lo) == len(self.hi) or any(a >= b for a, b in zip(self.lo, self.hi)):
            raise ValueError("each column needs a lower and a higher bound")

    @property
    def d(self) -> int:
        return len(self.columns)


def names(d: int) -> list[str]:
    return [f"x{i}" for i in range(d)]


def _scaled(c: Column, lo: float, hi: float, r: float) -> Column:
    return r * (2 * (c - lo) / (hi - lo) - 1)


def normalize(df: DataFrame, domain: Domain, keep: tuple[str, ...] = (), oob: str = "clamp") -> DataFrame:
    """x0.. in [-r, r].  Rows with a null or NaN are dropped; values outside are clamped, or their rows dropped."""
    values = [F.col(c).cast("double") for c in domain.columns]
    ok = F.lit(True)
    for v, lo, hi in zip(values, domain.lo, domain.hi):
        ok = ok & v.isNotNull() & ~F.isnan(v)
        if oob == "drop":
            ok = ok & v.between(lo, hi)
    scaled = [_scaled(F.least(F.greatest(v, F.lit(lo)), F.lit(hi)), lo, hi, domain.r).alias(x) for v, lo, hi, x in zip(values, domain.lo, domain.hi, names(domain.d))]
    return df.where(ok).select(*keep, *scaled)


def normalize_sql(exprs: list[str], domain: Domain) -> str:
    return ", ".join(f"{domain.r} * (2 * (least(greatest(CAST({e} AS DOUBLE), {lo}), {hi}) - {lo}) / ({hi} - {lo}) - 1) AS x{i}" for i, (e, lo, hi) in enumerate(zip(exprs, domain.lo, domain.hi)))


def denormalize(centroids: list[list[float]], domain: Domain) -> list[list[float]]:
    return [[lo + (x / domain.r + 1) / 2 * (hi - lo) for x, lo, hi in zip(c, domain.lo, domain.hi)] for c in centroids]
