"""The synopsis: noisy counts of equal cells of the box, empty ones included.

One scan and one partial aggregation give exact counts; every cell of the grid then gets Laplace
noise of scale 1 / epsilon, keyed by its number, and the result is the release: later loops read
cells and never the data.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger

THETA = 10.0
#: Boxes up to which a range count broadcasts them; more are joined by slabs.
MAX_BOXES = 10_000


def cells_2d(n: float, eps: float, theta: float = THETA) -> float:
    return n * eps / theta


def cells_general(n: float, eps: float, d: int, theta: float = THETA) -> float:
    """The number of cells that balances noise and the error of spreading points evenly within cells."""
    return (n * eps / theta) ** (2 * d / (2 + d))


def theta_from(alpha: float, beta: float) -> float:
    return math.sqrt(alpha / (2 * beta * beta))


@dataclass(frozen=True)
class GridSpec:
    m: tuple[int, ...]
    r: float = 1.0
    wanted: float = 0.0
    capped: bool = False

    @property
    def d(self) -> int:
        return len(self.m)

    @property
    def cells(self) -> int:
        return math.prod(self.m)


def grid_spec(cells: float, d: int, r: float = 1.0, rounding: str = "round", max_cells: int | None = None) -> GridSpec:
    """Intervals of each dimension, as the rule says; only an explicit max_cells makes them fewer.  mixed: counts that may differ by one, whose product is nearest to the rule's."""
    root, capped = max(cells, 1.0) ** (1 / d), False
    if rounding == "mixed":
        lo = max(1, math.floor(root))
        m = min((tuple([lo + 1] * i + [lo] * (d - i)) for i in range(d + 1)), key=lambda x: abs(math.prod(x) - cells))
    else:
        one = {"round": lambda x: math.floor(x + 0.5), "floor": math.floor, "ceil": math.ceil}[rounding](root)
        m = (max(1, one),) * d
    while max_cells and math.prod(m) > max_cells and max(m) > 1:
        m, capped = tuple(max(1, x - 1) if x == max(m) else x for x in m), True
    return GridSpec(m, r, cells, capped)


def cell_id(cols: list[str], spec: GridSpec) -> Column:
    out = F.lit(0).cast("long")
    for c, m in zip(cols, spec.m):
        out = out * m + F.greatest(F.lit(0), F.least(F.floor((F.col(c) + spec.r) / (2 * spec.r) * m), F.lit(m - 1)))
    return out


def cell_id_sql(spec: GridSpec) -> str:
    out = "0"
    for i, m in enumerate(spec.m):
        out = f"({out} * {m} + greatest(0, least(CAST(floor((x{i} + {spec.r}) / {2 * spec.r} * {m}) AS BIGINT), {m - 1})))"
    return f"CAST({out} AS BIGINT)"


def _strides(spec: GridSpec) -> list[int]:
    return [math.prod(spec.m[i + 1 :]) for i in range(spec.d)]


def cell_center(cell: Column | str, spec: GridSpec) -> list[Column]:
    c = F.col(cell) if isinstance(cell, str) else cell
    return [(F.lit(2 * spec.r) * (F.pmod(F.floor(c / s), F.lit(m)) + 0.5) / m - spec.r).alias(f"x{i}") for i, (m, s) in enumerate(zip(spec.m, _strides(spec)))]


def cell_center_sql(cell: str, spec: GridSpec) -> str:
    return ", ".join(f"{2 * spec.r} * (({cell} // {s}) % {m} + 0.5) / {m} - {spec.r} AS x{i}" for i, (m, s) in enumerate(zip(spec.m, _strides(spec))))


def cell_counts(df: DataFrame, cols: list[str], spec: GridSpec) -> DataFrame:
    return df.groupBy(cell_id(cols, spec).alias("cell")).count().withColumnRenamed("count", "n_exact")


def all_cells(df: DataFrame, cols: list[str], spec: GridSpec) -> DataFrame:
    """Exact counts of all cells; for tests and as the step before noise."""
    every = df.sparkSession.range(spec.cells).withColumnRenamed("id", "cell")
    return every.join(cell_counts(df, cols, spec), "cell", "left").select("cell", F.coalesce("n_exact", F.lit(0)).alias("n_exact"))


@dataclass
class Synopsis:
    """cells: (cell, n, x0..), n noisy.  A private output, for any number of uses."""

    cells: DataFrame
    spec: GridSpec
    eps: float
    theta: float = THETA
    ledger: BudgetLedger | None = None

    @property
    def cols(self) -> list[str]:
        return [f"x{i}" for i in range(self.spec.d)]

    def weighted(self, counts: str = "raw") -> DataFrame:
        """How counts weigh: raw keeps negative ones, which cancel noise elsewhere; round_nonneg and clip_zero are the biased variants."""
        n = F.col("n")
        w = {"raw": n, "round_nonneg": F.greatest(F.lit(0.0), F.floor(n + 0.5).cast("double")), "clip_zero": F.greatest(n, F.lit(0.0))}[counts]
        return self.cells.withColumn("n", w)

    def replicated(self) -> DataFrame:
        """The centre of each cell as often as its rounded count says."""
        times = F.greatest(F.lit(0), F.floor(F.col("n") + 0.5)).cast("int")
        return self.cells.where(times > 0).select("cell", *self.cols, F.explode(F.sequence(F.lit(1), times)).alias("copy"))

    def save(self, path: str) -> None:
        self.cells.orderBy("cell").write.mode("overwrite").parquet(f"{path}/cells")
        meta = [(list(self.spec.m), self.spec.r, self.eps, self.theta, self.spec.capped)]
        self.cells.sparkSession.createDataFrame(meta, "m array<int>, r double, eps double, theta double, capped boolean").coalesce(1).write.mode("overwrite").json(f"{path}/meta")

    @staticmethod
    def load(spark, path: str) -> Synopsis:
        meta = spark.read.schema("m array<int>, r double, eps double, theta double, capped boolean").json(f"{path}/meta").first()
        return Synopsis(spark.read.parquet(f"{path}/cells"), GridSpec(tuple(meta["m"]), meta["r"], capped=meta["capped"]), meta["eps"], meta["theta"])


def release_grid(df: DataFrame, cols: list[str], eps: float, n: float | None = None, theta: float = THETA, rounding: str = "round", max_cells: int | None = None, spec: GridSpec | None = None, source: NoiseSource | None = None, ledger: BudgetLedger | None = None, run: int = 0, at: str | None = None, r: float = 1.0) -> Synopsis:
    """n: the public number of rows (or a noisy one, paid for before), which the size rule needs where no spec is given.  at: a folder to which the release is written once."""
    source, ledger = source or NoiseSource.secret(), ledger or BudgetLedger(eps)
    spec = spec or grid_spec(cells_general(n, eps, len(cols), theta), len(cols), r, rounding, max_cells)
    ledger.parallel("cell counts", eps, spec.cells)
    out = Synopsis(_noisy(all_cells(df, cols, spec), spec, eps, source, run), spec, eps, theta, ledger)
    if at:
        out.save(at)
        out.cells = df.sparkSession.read.parquet(f"{at}/cells")
    return out


def noise_step(run: int, eps: float) -> str:
    """Noise of one run is never drawn again at another scale."""
    return f"grid-{run}-{eps:.9g}"


def _noisy(exact: DataFrame, spec: GridSpec, eps: float, source: NoiseSource, run: int) -> DataFrame:
    return exact.select("cell", (F.col("n_exact") + source.laplace(1 / eps, noise_step(run, eps), "cell")).alias("n"), *cell_center("cell", spec))


class Releases:
    """Several independent releases of one histogram, which is counted once: for experiments, each run pays the whole budget."""

    def __init__(self, df: DataFrame, cols: list[str], eps: float, n: float, theta: float = THETA, max_cells: int | None = None, source: NoiseSource | None = None, r: float = 1.0):
        self.eps, self.theta, self.source = eps, theta, source or NoiseSource.secret()
        self.spec = grid_spec(cells_general(n, eps, len(cols), theta), len(cols), r, max_cells=max_cells)
        self.exact = cell_counts(df, cols, self.spec).persist()

    def __enter__(self) -> Releases:
        return self

    def __exit__(self, *_) -> None:
        self.exact.unpersist()

    def synopsis(self, run: int) -> Synopsis:
        every = self.exact.sparkSession.range(self.spec.cells).withColumnRenamed("id", "cell")
        filled = every.join(self.exact, "cell", "left").select("cell", F.coalesce("n_exact", F.lit(0)).alias("n_exact"))
        ledger = BudgetLedger(self.eps)
        ledger.parallel("cell counts", self.eps, self.spec.cells)
        return Synopsis(_noisy(filled, self.spec, self.eps, self.source, run), self.spec, self.eps, self.theta, ledger)


def release_many(df: DataFrame, cols: list[str], eps: float, spec: GridSpec, runs: int, source: NoiseSource) -> DataFrame:
    """(run, cell, n, x0..): independent noises on one histogram, so one scan of the data; for experiments."""
    every = all_cells(df, cols, spec).withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    return every.select("run", "cell", (F.col("n_exact") + source.laplace(1 / eps, "grids", "run", "cell")).alias("n"), *cell_center("cell", spec))


def noisy_size(df: DataFrame, eps: float, source: NoiseSource, ledger: BudgetLedger) -> float:
    """The number of rows where it is not public."""
    ledger.spend("row count", eps)
    return max(1.0, df.agg((F.count("*") + source.laplace(1 / eps, "row-count", F.lit(0))).alias("n")).first()[0])


def range_count(synopsis: Synopsis, boxes: DataFrame) -> DataFrame:
    """(qid, est): whole cells count, cells on the border by their overlapped part.  boxes: qid, lo, hi arrays."""
    part = F.lit(1.0)
    for i, m in enumerate(synopsis.spec.m):
        w = 2 * synopsis.spec.r / m
        a, b = F.col(f"x{i}") - w / 2, F.col(f"x{i}") + w / 2
        part = part * F.greatest(F.lit(0.0), F.least(b, F.col("hi")[i]) - F.greatest(a, F.col("lo")[i])) / w
    touching = [(F.col(f"x{i}") + synopsis.spec.r / m > F.col("lo")[i]) & (F.col(f"x{i}") - synopsis.spec.r / m < F.col("hi")[i]) for i, m in enumerate(synopsis.spec.m)]
    on = touching[0]
    for t in touching[1:]:
        on = on & t
    few = boxes.limit(MAX_BOXES + 1).count() <= MAX_BOXES
    return synopsis.cells.join(F.broadcast(boxes) if few else boxes, on).groupBy("qid").agg(F.sum(F.col("n") * part).alias("est"))


def range_count_exact(df: DataFrame, cols: list[str], boxes: DataFrame) -> DataFrame:
    """Ground truth: a few boxes (a stated query set) against all rows; many boxes are joined by slabs."""
    if boxes.limit(MAX_BOXES + 1).count() > MAX_BOXES:
        return range_count_bucketed(df, cols, boxes, 4096)
    on = F.lit(True)
    for i, c in enumerate(cols):
        on = on & (F.col(c) >= F.col("lo")[i]) & (F.col(c) < F.col("hi")[i])
    return boxes.join(F.broadcast(boxes).alias("b").join(df, on).groupBy("b.qid").count(), "qid", "left").select("qid", F.coalesce("count", F.lit(0)).alias("n"))


def range_count_bucketed(df: DataFrame, cols: list[str], boxes: DataFrame, buckets: int = 16, r: float = 1.0) -> DataFrame:
    """The same as an equality join: boxes go to the slabs of the first dimension that they touch."""
    slab = lambda v: F.greatest(F.lit(0), F.least(F.floor((v + r) / (2 * r) * buckets), F.lit(buckets - 1)))
    spread = boxes.withColumn("slab", F.explode(F.sequence(slab(F.col("lo")[0]), slab(F.col("hi")[0]))))
    inside = F.lit(True)
    for i, c in enumerate(cols):
        inside = inside & (F.col(c) >= F.col("lo")[i]) & (F.col(c) < F.col("hi")[i])
    found = df.withColumn("slab", slab(F.col(cols[0]))).join(spread, "slab").where(inside).groupBy("qid").count()
    return boxes.select("qid").join(found, "qid", "left").select("qid", F.coalesce("count", F.lit(0)).alias("n"))


def synthesize(synopsis: Synopsis, n: int, source: NoiseSource) -> DataFrame:
    """n points spread evenly within cells drawn in proportion to their counts; needs no further budget."""
    from pyspark.sql import Window

    w = synopsis.weighted("clip_zero").where("n > 0")
    total = w.agg(F.sum("n")).first()[0]
    if not total:
        return w.select(F.lit(0).cast("long").alias("id"), *synopsis.cols).limit(0)
    w = w.withColumn("part", F.floor(F.col("cell") / 1024))
    parts = w.groupBy("part").agg(F.sum("n").alias("p")).withColumn("base", F.sum("p").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))
    inside = F.sum("n").over(Window.partitionBy("part").orderBy("cell").rowsBetween(Window.unboundedPreceding, 0))
    cum = w.withColumn("in", inside).join(parts, "part").withColumn("hi", (F.col("in") + F.coalesce("base", F.lit(0.0))) / total)
    share = cum.withColumn("copies", F.round(F.col("hi") * n) - F.round((F.col("hi") - F.col("n") / total) * n)).where("copies > 0")
    rows = share.withColumn("i", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    jitter = [(F.col(f"x{i}") + (source.uniform(f"synth-{i}", "cell", "i") - 0.5) * (2 * synopsis.spec.r / m)).alias(f"x{i}") for i, m in enumerate(synopsis.spec.m)]
    return rows.select("cell", F.col("i").alias("id"), *jitter)


def fixed_boxes(spark, d: int, n: int, seed: str = "boxes", r: float = 1.0) -> DataFrame:
    src, out = NoiseSource(seed), []
    for q in range(n):
        ends = [sorted((2 * src.draw("a", q, i) - 1, 2 * src.draw("b", q, i) - 1)) for i in range(d)]
        out.append((q, [round(a * r, 6) for a, _ in ends], [round(b * r, 6) for _, b in ends]))
    return spark.createDataFrame(out, "qid int, lo array<double>, hi array<double>")


def marginal_specs(spec: GridSpec) -> list[tuple[int, ...]]:
    return [c for n in range(spec.d + 1) for c in itertools.combinations(range(spec.d), n)]
