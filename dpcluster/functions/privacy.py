"""Budget, sensitivities, and private selection.

The unit of privacy is a row: neighbours differ by one row more or less.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource


class BudgetExceeded(ValueError):
    pass


@dataclass
class BudgetLedger:
    """What was spent.  Steps in sequence add up; steps over disjoint parts cost the dearest of them."""

    total: float
    rows: list[tuple[str, float, str, float, int]] = field(default_factory=list)

    @property
    def spent(self) -> float:
        return sum(r[1] for r in self.rows)

    def spend(self, step: str, eps: float, sensitivity: float = 1.0, queries: int = 1, scope: str = "sequence") -> float:
        if eps <= 0:
            raise ValueError("a step needs a positive budget")
        if self.spent + eps > self.total * (1 + 1e-9):
            raise BudgetExceeded(f"{step} asks for {eps:g}, {self.total - self.spent:g} are left")
        self.rows.append((step, eps, scope, sensitivity, queries))
        return eps

    def parallel(self, step: str, eps: float, parts: int, sensitivity: float = 1.0) -> float:
        """One answer from each of disjoint parts: a row is in one of them."""
        return self.spend(step, eps, sensitivity, parts, "disjoint")

    def split(self, weights) -> list[float]:
        return [(self.total - self.spent) * w / sum(weights) for w in weights]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "step string, epsilon double, scope string, sensitivity double, queries int")


class sensitivity:
    """L1 sensitivities of the queries that the methods ask."""

    @staticmethod
    def count() -> float:
        return 1.0

    @staticmethod
    def bounded_sum(r: float = 1.0) -> float:
        return r

    @staticmethod
    def centroid_update(d: int, r: float = 1.0) -> float:
        return d * r + 1

    @staticmethod
    def fitness(d: int, r: float = 1.0) -> float:
        return 4 * d * r * r

    @staticmethod
    def block_mean(lo: float, hi: float, blocks: int) -> float:
        return (hi - lo) / blocks


def neighbours(df: DataFrame, key: Column) -> DataFrame:
    """The table without the rows of a key."""
    return df.where(~key)


def exp_select(df: DataFrame, score: str, key: str, eps_pick: float, sens: float, source: NoiseSource, step: str, n: int = 1) -> DataFrame:
    """n rows by the exponential mechanism without replacement: the largest scores with Gumbel noise added.

    Each pick is charged ``eps_pick``."""
    noisy = F.col(score) * (eps_pick / (2 * sens)) + source.gumbel(step, key)
    return df.withColumn("noisy", noisy).orderBy(F.desc("noisy"), F.asc(key)).limit(n)


def private_range(df: DataFrame, cols: list[str], lo: float, hi: float, eps: float, n_rows: int, source: NoiseSource, q=(0.05, 0.95), bins: int = 1024, clip: bool = True, slack: float = 1.0) -> DataFrame:
    """(dim, lo, hi): two quantiles of each column by the exponential mechanism over public bins.

    Without ``clip`` the bins cover ``slack`` times the width of the box beyond it on either side, and the outcome may lie outside the box."""
    wide = 0.0 if clip else slack * (hi - lo)
    low, width = lo - wide, (hi - lo + 2 * wide) / bins
    spark = df.sparkSession
    dims = F.explode(F.array(*(F.struct(F.lit(i).alias("dim"), F.col(c).alias("v")) for i, c in enumerate(cols)))).alias("e")
    hist = df.select(dims).select("e.dim", F.least(F.floor((F.col("e.v") - low) / width), F.lit(bins - 1)).alias("bin")).groupBy("dim", "bin").count()
    every = spark.range(len(cols) * bins).select(F.expr(f"cast(id div {bins} as int)").alias("dim"), F.expr(f"id % {bins}").alias("bin"))
    upto = Window.partitionBy("dim").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    ranks = every.join(hist, ["dim", "bin"], "left").withColumn("rank", F.sum(F.coalesce("count", F.lit(0))).over(upto))
    share, out = eps / (len(q) * len(cols)), None
    for name, quantile in zip(("lo", "hi"), q):
        noisy = -F.abs(F.col("rank") - quantile * n_rows) * (share / 2) + source.gumbel(f"range-{name}", "dim", "bin")
        best = ranks.withColumn("noisy", noisy).groupBy("dim").agg((F.max_by("bin", F.struct("noisy", -F.col("bin"))) * width + low + (width if name == "hi" else 0.0)).alias(name))
        out = best if out is None else out.join(best, "dim")
    lo_, hi_ = F.least("lo", "hi"), F.greatest("lo", "hi")
    if clip:
        lo_, hi_ = F.greatest(lo_, F.lit(lo)), F.least(hi_, F.lit(hi))
    return out.select("dim", lo_.alias("lo"), hi_.alias("hi"))
