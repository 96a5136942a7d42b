"""Stand-ins for the experiment data on the given tables, with public bounds, and generated clusters."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpcluster.functions.domain import Domain, names, normalize, normalize_sql
from dpcluster.functions.noise import NoiseSource
from dpcluster.operators.centroids import packed_init

DAY0 = "1995-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _day(c: str) -> tuple[str, str]:
    return f"datediff({c}, DATE '{DAY0}')", f"date_diff('day', DATE '{DAY0}', CAST({c} AS DATE))"


def _same(c: str) -> tuple[str, str]:
    return c, c


_SECOND = ("hour(ts) * 3600 + minute(ts) * 60 + second(ts)", "hour(ts) * 3600 + minute(ts) * 60 + second(ts)")
_LINE = [(_same("l_quantity"), 0, 51), (_same("l_extendedprice"), 0, 105000), (_same("l_discount"), 0, 0.1), (_same("l_tax"), 0, 0.08), (_same("l_linenumber"), 1, 7), (_day("l_shipdate"), 0, 2600)]
_STAR = [*_LINE, (_same("o_totalprice"), 0, 500000), (_day("o_orderdate"), 0, 2500), (_same("c_acctbal"), -1000, 10000), (_same("p_size"), 0, 51)]


@dataclass(frozen=True)
class Workload:
    """features: ((Spark text, DuckDB text), lo, hi); sql_from: the rows in SQL; distinct: unique points only."""

    name: str
    k: int
    features: tuple
    sql_from: str
    distinct: bool = False

    @property
    def d(self) -> int:
        return len(self.features)

    @property
    def cols(self) -> list[str]:
        return names(self.d)

    @property
    def domain(self) -> Domain:
        return Domain(tuple(f"f{i}" for i in range(self.d)), tuple(float(lo) for _, lo, _ in self.features), tuple(float(hi) for *_, hi in self.features))

    def source(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        if self.name == "D6":
            line, orders, customer, part = (table(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "part"))
            return line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
        return table(spark, sf_dir, self.sql_from)

    def points(self, spark: SparkSession, sf_dir: str, keep: tuple[str, ...] = ()) -> DataFrame:
        """keep: columns beside the points, such as the key of a row."""
        df = self.source(spark, sf_dir).select(*keep, *(F.expr(e[0]).cast("double").alias(f"f{i}") for i, (e, _, _) in enumerate(self.features)))
        return normalize(df.dropDuplicates() if self.distinct else df, self.domain, keep)

    def points_sql(self, keep: str = "") -> str:
        rows = f"SELECT {'DISTINCT ' if self.distinct else ''}{keep + ', ' if keep else ''}{', '.join(f'CAST({e[1]} AS DOUBLE) AS f{i}' for i, (e, _, _) in enumerate(self.features))} FROM {self.sql_from}"
        return f"SELECT {keep + ', ' if keep else ''}{normalize_sql([f'f{i}' for i in range(self.d)], self.domain)} FROM ({rows}) raw"


_TEXT = [(("ln(1 + n_chars)",) * 2, 0, 12), (("n_chars / (1.0 + length(text) - length(replace(text, ' ', '')))",) * 2, 0, 20), (("(length(text) - length(regexp_replace(text, '[0-9]', '')))  / (1.0 + length(text))", "(length(text) - length(regexp_replace(text, '[0-9]', '', 'g')))  / (1.0 + length(text))"), 0, 1)]

WORKLOADS = {
    w.name: w
    for w in (
        Workload("D1", 15, ((_same("c_acctbal"), -1000, 10000), (_same("c_nationkey"), 0, 24)), "customer"),
        Workload("D2", 5, ((_SECOND, 0, 86400), (_same("value"), 0, 500)), "events", True),
        Workload("D3", 2, ((_same("o_totalprice"), 0, 500000), (_day("o_orderdate"), 0, 2500)), "orders"),
        Workload("D4", 3, ((_same("l_quantity"), 0, 51), (_same("l_discount"), 0, 0.1), (_same("l_tax"), 0, 0.08)), "lineitem"),
        Workload("D5", 5, tuple(_LINE), "lineitem"),
        Workload("D6", 3, tuple(_STAR), "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey"),
        Workload("D7", 10, tuple(((f"embedding[{i}]", f"embedding[{i + 1}]"), -0.5, 0.5) for i in range(10)), "embeddings"),
        Workload("D8", 4, tuple(_TEXT), "documents"),
    )
}


def hash_sample(df: DataFrame, percent: int, *keys: str) -> DataFrame:
    """A repeatable share of the rows by a hash of their keys."""
    return df.where(F.conv(F.substring(F.md5(F.concat_ws("|", *(F.col(k).cast("string") for k in keys)).cast("binary")), 1, 8), 16, 10).cast("bigint") % 100 < percent)


def stratified_sample(df: DataFrame, stratum: str, percents: dict, rest: int, *keys: str) -> DataFrame:
    """As hash_sample, with a share for each value of a column."""
    share = F.coalesce(*(F.when(F.col(stratum) == v, p) for v, p in percents.items()), F.lit(rest))
    return df.where(F.conv(F.substring(F.md5(F.concat_ws("|", *(F.col(k).cast("string") for k in keys)).cast("binary")), 1, 8), 16, 10).cast("bigint") % 100 < share)


def gaussian_clusters(spark: SparkSession, n: int, d: int, k: int, sigma: float = 0.08, seed: int = 0, r: float = 1.0) -> DataFrame:
    """n points in k equal clusters around packed centres, from keyed noise; id and cluster beside the coordinates."""
    centres, src = packed_init(k, d, seed, r, tries=100, rounds=14)[0], NoiseSource(f"gauss-{seed}")
    base = spark.range(n).withColumn("cluster", (F.col("id") % k).cast("int"))
    xs = [F.greatest(F.lit(-r), F.least(F.lit(r), F.element_at(F.array(*(F.lit(float(c[i])) for c in centres)), F.col("cluster") + 1) + sigma * src.normal(f"x{i}", "id"))).alias(f"x{i}") for i in range(d)]
    return base.select("id", "cluster", *xs)


def gaussian_clusters_sql(n: int, d: int, k: int, sigma: float = 0.08, seed: int = 0) -> str:
    centres, src = packed_init(k, d, seed, 1.0, tries=100, rounds=14)[0], NoiseSource(f"gauss-{seed}")
    xs = []
    for i in range(d):
        pick = " ".join(f"WHEN {j} THEN {c[i]!r}" for j, c in enumerate(centres))
        xs.append(f"greatest(-1.0, least(1.0, CASE id % {k} {pick} END + {sigma} * {src.normal_sql(f'x{i}', 'id')})) AS x{i}")
    return f"SELECT id, CAST(id % {k} AS INTEGER) AS cluster, {', '.join(xs)} FROM (SELECT range AS id FROM range({n})) t"


#: Rows, dimensions, clusters of the published data sets.
PUBLISHED = (("S", 5000, 2, 15), ("checkins", 107091, 2, 5), ("roads", 16281, 2, 2), ("colours", 34112, 3, 3), ("census", 48841, 6, 5), ("components", 26733, 10, 3), ("generated", 10000, 5, 5))
