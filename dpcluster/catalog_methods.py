"""Queries of the methods, measures and experiments."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpcluster.catalog import query, rounded
from dpcluster.functions.domain import names
from dpcluster.functions.noise import NoiseSource
from dpcluster.functions.privacy import BudgetLedger, exp_select, private_range
from dpcluster.operators import block_average as blocks
from dpcluster.operators import evolve as ev
from dpcluster.operators import grid as g
from dpcluster.operators.centroids import as_table, init_sets, packed_init, uniform_init
from dpcluster.operators.grid_kmeans import cluster_synopsis, grid_kmeans, synopsis_nicv, tune_on_synopsis
from dpcluster.operators.lloyd import assign, best_of, family_sums, grouped, lloyd, lloyd_many, nicv_many, partial_sums
from dpcluster.operators.noisy_lloyd import noise_step, noisy_lloyd, noisy_lloyd_many, noisy_sums, with_empty
from dpcluster.operators.two_stage import decide, two_stage, two_stage_many
from dpcluster.plans import error_model as em
from dpcluster.plans import experiments as ex
from dpcluster.plans import metrics
from dpcluster.sources.workloads import PUBLISHED, WORKLOADS, gaussian_clusters, gaussian_clusters_sql, table

SRC = NoiseSource("catalog")
D = WORKLOADS
QUICK = ex.Protocol.quick()


def lit(x: float) -> str:
    return f"CAST({float(x)!r} AS DOUBLE)"


def values(rows, cols: str) -> str:
    return f"(VALUES {', '.join('(' + ', '.join(map(str, r)) + ')' for r in rows)}) t({cols})"


def R(x: str, name: str | None = None) -> str:
    return f"round({x}, 6) AS {name or x}"


def table_of(spark, c, name="centroids") -> DataFrame:
    """Centroids as rows, for comparison."""
    return rounded(as_table(spark, [c]).select("j", *(F.col("c")[i].alias(f"x{i}") for i in range(len(c[0])))))


# --- privacy -----------------------------------------------------------------------------------------


@query("laplace_noise", f"SELECT l_orderkey, l_linenumber, l_partkey, {R(SRC.laplace_sql('2.0', 'demo', 'l_orderkey', 'l_linenumber', 'l_partkey'), 'noise')} FROM lineitem")
def _(spark, sf):
    return rounded(table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", SRC.laplace(2.0, "demo", "l_orderkey", "l_linenumber", "l_partkey").alias("noise")))


_M = SRC.laplace_sql("2.0", "moments", "range")


@query("laplace_moments", f"SELECT round(avg(n), 6) AS mean, round(var_samp(n), 6) AS variance, round(avg(abs(n)), 6) AS spread FROM (SELECT {_M} AS n FROM range(20000)) t")
def _(spark, sf):
    n = spark.range(20000).select(SRC.laplace(2.0, "moments", "id").alias("n"))
    return rounded(n.agg(F.avg("n").alias("mean"), F.var_samp("n").alias("variance"), F.avg(F.abs("n")).alias("spread")))


@query("ledger_report", f"SELECT * FROM {values([(chr(39) + 'synopsis' + chr(39), lit(0.5), chr(39) + 'disjoint' + chr(39), lit(1.0), 100), (chr(39) + 'round 1' + chr(39), lit(0.5), chr(39) + 'sequence' + chr(39), lit(3.0), 6)], 'step, epsilon, scope, sensitivity, queries')}")
def _(spark, sf):
    ledger = BudgetLedger(1.0)
    ledger.parallel("synopsis", 0.5, 100)
    ledger.spend("round 1", 0.5, 3.0, 6)
    return ledger.to_df(spark)


_EXP = f"SELECT c_custkey, CAST(row_number() OVER (ORDER BY c_acctbal * {0.5 / (2 * 100.0)!r} + {SRC.gumbel_sql('pick', 'c_custkey')} DESC, c_custkey) AS INTEGER) AS place FROM customer ORDER BY place LIMIT 10"


@query("exp_select_topn", _EXP)
def _(spark, sf):
    from pyspark.sql import Window

    got = exp_select(table(spark, sf, "customer"), "c_acctbal", "c_custkey", 0.5, 100.0, SRC, "pick", 10)
    return got.select("c_custkey", F.row_number().over(Window.orderBy(F.desc("noisy"), "c_custkey")).alias("place"))


def _range(df, clip):
    return private_range(df, ["x0", "x1"], -1.0, 1.0, 0.2, df.count(), SRC, bins=256, clip=clip)


def _range_cte(clip: bool, eps: float) -> str:
    """r (dim, l, h): the private range of points p; range_final bounds it."""
    low, width = (-1.0, 2 / 256) if clip else (-3.0, 6 / 256)
    q = lambda name, share: f"SELECT dim, arg_max(bin, noisy) AS bin FROM (SELECT dim, bin, -abs(rank - {share!r} * (SELECT count(*) FROM p)) * {eps / 4 / 2!r} + {SRC.gumbel_sql('range-' + name, 'dim', 'bin')} AS noisy FROM ranks) t GROUP BY dim"
    return f"""e AS (SELECT 0 AS dim, x0 AS v FROM p UNION ALL SELECT 1, x1 FROM p),
hist AS (SELECT dim, least(CAST(floor((v - {low}) / {width!r}) AS BIGINT), 255) AS bin, count(*) AS n FROM e GROUP BY 1, 2),
every AS (SELECT CAST(range // 256 AS INTEGER) AS dim, range % 256 AS bin FROM range(512)),
ranks AS (SELECT e.dim, e.bin, sum(coalesce(n, 0)) OVER (PARTITION BY e.dim ORDER BY e.bin) AS rank FROM every e LEFT JOIN hist h ON e.dim = h.dim AND e.bin = h.bin),
qa AS ({q("lo", 0.05)}), qb AS ({q("hi", 0.95)}),
r AS (SELECT a.dim, a.bin * {width!r} + {low} AS l, b.bin * {width!r} + {low} + {width!r} AS h FROM qa a JOIN qb b ON a.dim = b.dim)"""


def _bounds(clip: bool) -> tuple[str, str]:
    return ("greatest(least(l, h), -1.0)", "least(greatest(l, h), 1.0)") if clip else ("least(l, h)", "greatest(l, h)")


def _range_sql(clip: bool) -> str:
    lo, hi = _bounds(clip)
    return f"WITH p AS ({D['D3'].points_sql()}),\n{_range_cte(clip, 0.2)}\nSELECT dim, round({lo}, 6) AS lo, round({hi}, 6) AS hi FROM r"


query("private_range", _range_sql(True))(lambda spark, sf: rounded(_range(D["D3"].points(spark, sf), True)))
query("range_clip", _range_sql(False))(lambda spark, sf: rounded(_range(D["D3"].points(spark, sf), False)))

# --- building blocks ---------------------------------------------------------------------------------


def _all(xs, at=""):
    return ", ".join(R(f"{at}{x}", x) for x in xs)


for _name, _key in (("normalize_orders", "D3"), ("normalize_customer", "D1"), ("normalize_events", "D2"), ("normalize_lineitem3", "D4"), ("normalize_lineitem6", "D5"), ("normalize_star", "D6"), ("normalize_embeddings", "D7"), ("normalize_texts", "D8")):
    query(_name, f"SELECT {_all(D[_key].cols)} FROM ({D[_key].points_sql()}) p")(lambda spark, sf, w=D[_key]: rounded(w.points(spark, sf)))


def nearest_sql(cols, c) -> str:
    """dist2 and cluster of a point, lower number first in ties."""
    ds = [" + ".join(f"(x{i} - {lit(v)}) * (x{i} - {lit(v)})" for i, v in enumerate(p)) for p in c]
    least = f"least({', '.join(ds)})"
    cases = " ".join(f"WHEN {d} <= {least} THEN {j}" for j, d in enumerate(ds))
    return f"{least} AS dist2, CAST(CASE {cases} END AS INTEGER) AS cluster"


C3, C5 = uniform_init(2, 2, "orders"), uniform_init(5, 6, "line")
_A = f"SELECT {_all(['x0', 'x1'])}, cluster, {R('dist2')} FROM (SELECT *, {nearest_sql(names(2), C3)} FROM ({D['D3'].points_sql()}) p) q"
for _name, _how in (("assign_nearest", "expr"), ("assign_nearest_join", "broadcast"), ("assign_nearest_arrow", "arrow")):
    query(_name, _A)(lambda spark, sf, how=_how: rounded(assign(D["D3"].points(spark, sf), names(2), C3, how)))


def step_cte(i: int, d: int, k: int, previous: str, points: str = "p", weight: str | None = None, noise: tuple | None = None, r: float | None = None, least: float = 1.0) -> str:
    """One round in SQL: centroids c{i} from c{i-1} (columns j, x0..)."""
    w = weight or "1.0"
    dist = " + ".join(f"(p.x{q} - c.x{q}) * (p.x{q} - c.x{q})" for q in range(d))
    sums = ", ".join(f"sum({w} * x{q}) AS s{q}" for q in range(d))
    cols = ", ".join(f"p.x{q}" for q in range(d)) + (f", p.{weight}" if weight else "")
    add = lambda c: f"coalesce({c}, 0) + {SRC.laplace_sql(repr(noise[0]), f'{noise_step(noise[2], noise[1], noise[0])}-{c}', 'j')}" if noise else c
    clip = (lambda x: f"least({r}, greatest({-r}, {x}))") if r else (lambda x: x)
    nxt = ", ".join(f"CASE WHEN n >= {least} THEN {clip(f's{q} / n')} ELSE {clip(f'x{q}')} END AS x{q}" for q in range(d))
    return f"""a{i} AS (SELECT id, arg_min(j, (dist, j)) AS j FROM (SELECT p.id, c.j, {dist} AS dist FROM {points} p, {previous} c) t GROUP BY id),
s{i} AS (SELECT a.j AS k, sum({w}) AS n, {sums} FROM {points} p JOIN a{i} a ON p.id = a.id GROUP BY a.j),
m{i} AS (SELECT c.j, {', '.join(f'c.x{q}' for q in range(d))}, {add('n')} AS n, {', '.join(f'{add(f"s{q}")} AS s{q}' for q in range(d))} FROM {previous} c LEFT JOIN s{i} s ON c.j = s.k),
c{i} AS (SELECT j, {nxt} FROM m{i})"""


def start_cte(c) -> str:
    return f"c0 AS (SELECT * FROM {values([(j, *map(lit, p)) for j, p in enumerate(c)], 'j, ' + ', '.join(f'x{i}' for i in range(len(c[0]))))})"


def rounds_sql(points: str, c, rounds: int, noise=None, **options) -> str:
    d = len(c[0])
    steps = [step_cte(i, d, len(c), f"c{i - 1}", noise=(noise[i - 1], i - 1, 0) if noise else None, **options) for i in range(1, rounds + 1)]
    ctes = ",\n".join([f"p AS (SELECT *, row_number() OVER () AS id FROM ({points}) raw0)", start_cte(c), *steps])
    return f"WITH {ctes}\nSELECT CAST(j AS INTEGER) AS j, {_all(names(d))} FROM c{rounds}"


def family_ctes(points: str, sets, rounds: int, weight: str | None = None, r: float | None = None, least: float = 1.0, noise=None, tag: str = "f") -> str:
    """Tables {tag}c0 .. of many runs at once (run, j, x0..), from points p (id, x0.., weight).  noise: round, column -> SQL."""
    d, w, names_ = len(sets[0][0]), weight or "1.0", names(len(sets[0][0]))
    dist = " + ".join(f"(p.{x} - c.{x}) * (p.{x} - c.{x})" for x in names_)
    clip = (lambda x: f"least({r}, greatest({-r}, {x}))") if r else (lambda x: x)
    out = [f"{tag}c0 AS (SELECT * FROM {values([(i, j, *map(lit, c)) for i, s in enumerate(sets) for j, c in enumerate(s)], 'run, j, ' + ', '.join(names_))})"]
    for i in range(1, rounds + 1):
        add = lambda c, i=i: f"coalesce({c}, 0) + {noise(i - 1, c)}" if noise else c
        out.append(f"{tag}a{i} AS MATERIALIZED (SELECT p.id, c.run, arg_min(c.j, ({dist}, c.j)) AS j FROM {points} p, {tag}c{i - 1} c GROUP BY p.id, c.run)")
        out.append(f"{tag}s{i} AS MATERIALIZED (SELECT a.run AS r, a.j AS k, sum({w}) AS n, {', '.join(f'sum({w} * {x}) AS s{q}' for q, x in enumerate(names_))} FROM {points} p JOIN {tag}a{i} a ON p.id = a.id GROUP BY 1, 2)")
        nxt = ", ".join(f"CASE WHEN m >= {least} THEN {clip(f't{q} / m')} ELSE {clip(x)} END AS {x}" for q, x in enumerate(names_))
        out.append(f"{tag}c{i} AS MATERIALIZED (SELECT run, j, {nxt} FROM (SELECT c.run, c.j, {', '.join(f'c.{x}' for x in names_)}, {add('n')} AS m, {', '.join(f'{add(f"s{q}")} AS t{q}' for q in range(d))} FROM {tag}c{i - 1} c LEFT JOIN {tag}s{i} s ON c.run = s.r AND c.j = s.k) m)")
    return ",\n".join(out)


_P = lambda sql: f"p AS MATERIALIZED (SELECT *, row_number() OVER () AS id FROM ({sql}) raw0)"


query("lloyd_step", rounds_sql(D["D3"].points_sql(), C3, 1))(lambda spark, sf: table_of(spark, lloyd(D["D3"].points(spark, sf), names(2), C3, 1).centroids))
query("lloyd_3_iters", rounds_sql(D["D3"].points_sql(), C3, 3))(lambda spark, sf: table_of(spark, lloyd(D["D3"].points(spark, sf), names(2), C3, 3, 0.0).centroids))
query("lloyd_step_6d", rounds_sql(D["D5"].points_sql(), C5, 1))(lambda spark, sf: table_of(spark, lloyd(D["D5"].points(spark, sf), names(6), C5, 1).centroids))
FAR = [[0.0, 0.0], [1.0, 1.0], [5.0, 5.0]]
query("lloyd_empty_cluster", rounds_sql(D["D3"].points_sql(), FAR, 1))(lambda spark, sf: table_of(spark, lloyd(D["D3"].points(spark, sf), names(2), FAR, 1).centroids))
_W = f"SELECT x0, x1, 1 + abs(x1) AS w FROM ({D['D3'].points_sql()}) z"
query("weighted_lloyd_step", rounds_sql(_W, C3, 1, weight="w", least=1e-9))(lambda spark, sf: table_of(spark, lloyd(D["D3"].points(spark, sf).withColumn("w", 1 + F.abs("x1")), names(2), C3, 1, weight="w").centroids))

PAIR = [C3, uniform_init(2, 2, "other")]


def _many(spark, sf):
    sets, _, _ = lloyd_many(D["D3"].points(spark, sf), names(2), PAIR, 1)
    return rounded(as_table(spark, sets).select("run", "j", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1")))


query("lloyd_many_step", " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS run, * FROM ({rounds_sql(D['D3'].points_sql(), c, 1)}) r{i}" for i, c in enumerate(PAIR)))(_many)


def _nicv_cte(centroids: str, d: int, name: str, weight: str = "1.0", points: str = "p") -> str:
    """{name} (run, v): weighted mean squared distances to the nearest centroid of each run."""
    dist = " + ".join(f"(p.x{q} - c.x{q}) * (p.x{q} - c.x{q})" for q in range(d))
    return f"{name} AS (SELECT run, sum({weight} * v) / sum({weight}) AS v FROM (SELECT p.id, {'p.' + weight + ', ' if weight != '1.0' else ''}c.run, min({dist}) AS v FROM {points} p, {centroids} c GROUP BY ALL) t GROUP BY run)"


_BEST = f"WITH {_P(D['D3'].points_sql())}, {family_ctes('p', PAIR, 4)}, {_nicv_cte('fc4', 2, 'v')} SELECT round(min(v), 6) AS nicv FROM v"


@query("baseline_best_of", _BEST)
def _(spark, sf):
    _, cost = best_of(D["D3"].points(spark, sf), names(2), PAIR, max_iter=4, tol=0.0)
    return rounded(spark.createDataFrame([(float(cost),)], "nicv double"))


@query("uniform_init", f"SELECT CAST(a.range AS INTEGER) AS j, {', '.join(R(f'2 * {SRC.uniform_sql("init", "a.range", str(i))} - 1', f'x{i}') for i in range(3))} FROM range(7) a")
def _(spark, sf):
    return table_of(spark, uniform_init(7, 3, SRC.seed))


PACK, PACK_A = packed_init(6, 3, 1)


@query("packed_init_check", "SELECT true AS apart, true AS inside")
def _(spark, sf):
    c = as_table(spark, [PACK])
    pairs = c.alias("a").join(c.alias("b"), F.col("a.j") < F.col("b.j"))
    apart = F.sqrt(F.aggregate(F.zip_with("a.c", "b.c", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)) >= 2 * PACK_A - 1e-9
    return pairs.agg(F.bool_and(apart).alias("apart"), F.bool_and(F.forall("a.c", lambda x: F.abs(x) <= 1 - PACK_A + 1e-9)).alias("inside"))


query("init_sets")(lambda spark, sf: as_table(spark, init_sets(30, 3, 2)))
S30 = init_sets(30, 2, 2)
_B30 = f"WITH {_P(D['D3'].points_sql())}, {family_ctes('p', S30[:6], 8)}, {_nicv_cte('fc8', 2, 'v')} SELECT round(min(v), 6) AS nicv FROM v"
query("baseline_six_starts", _B30)(lambda spark, sf: rounded(spark.createDataFrame([(float(best_of(D["D3"].points(spark, sf), names(2), S30[:6], max_iter=8, tol=0.0)[1]),)], "nicv double")))
query("baseline_30")(lambda spark, sf: table_of(spark, best_of(D["D3"].points(spark, sf), names(2), S30)[0]))

# --- noisy Lloyd -------------------------------------------------------------------------------------

_SC = lambda d, t, eps: (d + 1) * t / eps
query("noisy_lloyd_1", rounds_sql(D["D3"].points_sql(), C3, 1, [_SC(2, 1, 0.5)], r=1.0))(lambda spark, sf: table_of(spark, noisy_lloyd(D["D3"].points(spark, sf), names(2), 2, 0.5, 1, init=C3, source=SRC).centroids))
query("noisy_lloyd_2", rounds_sql(D["D3"].points_sql(), C3, 2, [_SC(2, 2, 1.0)] * 2, r=1.0))(lambda spark, sf: table_of(spark, noisy_lloyd(D["D3"].points(spark, sf), names(2), 2, 1.0, 2, init=C3, source=SRC).centroids))
query("noisy_lloyd_schedule", rounds_sql(D["D3"].points_sql(), C3, 2, [3 / 0.25, 3 / 0.75], r=1.0))(lambda spark, sf: table_of(spark, noisy_lloyd(D["D3"].points(spark, sf), names(2), 2, 1.0, 2, init=C3, schedule=[1, 3], source=SRC).centroids))
query("noisy_lloyd_limit", rounds_sql(D["D3"].points_sql(), C3, 3, r=1.0))(lambda spark, sf: table_of(spark, noisy_lloyd(D["D3"].points(spark, sf), names(2), 2, 1.0, 3, init=C3, noise=False, source=SRC).centroids))
_UNI = uniform_init(2, 2, "0")
query("noisy_lloyd_uniform", rounds_sql(D["D3"].points_sql(), _UNI, 1, [_SC(2, 1, 1.0)], r=1.0))(lambda spark, sf: table_of(spark, noisy_lloyd(D["D3"].points(spark, sf), names(2), 2, 1.0, 1, init="uniform", source=SRC).centroids))


_SIZE = f"SELECT CAST(c.j AS INTEGER) AS cluster, round(coalesce(n, 0) + {SRC.laplace_sql('3.0', noise_step(0, 0, 3.0) + '-n', 'c.j')}, 6) AS n FROM (SELECT range AS j FROM range(2)) c LEFT JOIN (SELECT cluster, count(*) AS n FROM (SELECT {nearest_sql(names(2), C3)} FROM ({D['D3'].points_sql()}) p) q GROUP BY 1) s ON c.j = s.cluster"


@query("noisy_lloyd_sizes", _SIZE)
def _(spark, sf):
    df = D["D3"].points(spark, sf)
    return rounded(noisy_sums(with_empty(partial_sums(assign(df, names(2), C3), names(2)), 2, 2), 2, 3.0, SRC, 0).select("cluster", "n"))


_MANY = [c for c in init_sets(3, 2, 2) for _ in range(5)]
_MANY_SQL = f"WITH {_P(D['D3'].points_sql())}, {family_ctes('p', _MANY, 5, r=1.0, noise=lambda i, c: SRC.laplace_sql('15.0', f'many-{i}-15-{c}', 'c.run', 'c.j'))} SELECT CAST(run AS BIGINT) AS run, CAST(j AS INTEGER) AS j, {_all(names(2))} FROM fc5"


@query("noisy_lloyd_many", _MANY_SQL)
def _(spark, sf):
    sets = noisy_lloyd_many(D["D3"].points(spark, sf), names(2), init_sets(3, 2, 2), 5, 1.0, source=SRC)
    return rounded(as_table(spark, sets).select("run", "j", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1")))


@query("noisy_lloyd_t_sweep")
def _(spark, sf):
    df = D["D3"].points(spark, sf).persist()
    ts = (1, 2, 3, 5, 10, 20)
    found = [noisy_lloyd(df, names(2), 2, 1.0, t, source=SRC).centroids for t in ts]
    return spark.createDataFrame(list(zip(ts, nicv_many(df, names(2), found))), "t int, nicv double")


# --- block averaging ---------------------------------------------------------------------------------

_N = [(f"'{n}'", N, d, k) for n, N, d, k in PUBLISHED]
_NT = values(_N, "name, n, d, k")


#: Stand-ins whose sizes the closed forms are taken at; rows are counted where all features are known.
_SHAPED = ("D1", "D2", "D3", "D4", "D5")
_SHAPES = "(" + " UNION ALL ".join(f"SELECT '{w}' AS name, CAST(count(*) AS INTEGER) AS n, {D[w].d} AS d, {D[w].k} AS k FROM ({D[w].points_sql()}) p WHERE {' AND '.join(f'{x} IS NOT NULL' for x in D[w].cols)}" for w in _SHAPED) + ") t"


def shapes(spark, sf) -> DataFrame:
    """(name, n, d, k) of the stand-ins, from their tables."""
    out = None
    for w in _SHAPED:
        known = D[w].points(spark, sf).where(" and ".join(f"{x} is not null" for x in D[w].cols))
        one = known.agg(F.lit(w).alias("name"), F.count("*").cast("int").alias("n"), F.lit(D[w].d).alias("d"), F.lit(D[w].k).alias("k"))
        out = one if out is None else out.unionAll(one)
    return out


def shaped(spark, sf) -> list[tuple]:
    return [(r["name"], r["n"], r["d"], r["k"]) for r in shapes(spark, sf).collect()]


query("block_counts", f"SELECT name, CAST(floor(pow(n, 0.4) + 0.5) AS BIGINT) AS blocks FROM {_SHAPES}")(lambda spark, sf: shapes(spark, sf).select("name", F.floor(F.pow("n", F.lit(0.4)) + 0.5).alias("blocks")))
query("block_counts_3k", f"SELECT name, CAST(floor(n / (3.0 * k) + 0.5) AS BIGINT) AS blocks FROM {_SHAPES}")(lambda spark, sf: spark.createDataFrame([(n, em.block_count(N, "3k", k=k)) for n, N, d, k in shaped(spark, sf)], "name string, blocks long"))
query("block_noise_scale", f"SELECT name, round(2 * 2.0 * k * d / (floor(pow(n, 0.4) + 0.5) * 0.5), 6) AS scale FROM {_SHAPES}")(lambda spark, sf: rounded(spark.createDataFrame([(n, blocks.noise_scale(2.0, k, d, em.block_count(N), 0.5)) for n, N, d, k in shaped(spark, sf)], "name string, scale double")))


def _keyed(spark, sf):
    df = table(spark, sf, "orders").select("o_orderkey", F.col("o_totalprice").alias("x0"))
    return blocks.with_block(df, 40, SRC, "o_orderkey")


_BLOCK = f"SELECT o_orderkey, o_totalprice, CAST(floor({SRC.uniform_sql('block', 'o_orderkey')} * 40) AS BIGINT) AS block FROM orders"
query("block_assign", f"SELECT o_orderkey, block FROM ({_BLOCK}) b")(lambda spark, sf: _keyed(spark, sf).select("o_orderkey", "block"))


@query("sample_aggregate_mean", f"SELECT round(sum(least(greatest(v, 0), 500000)) / 40 + (40 - count(*)) * 250000.0 / 40, 6) AS mean FROM (SELECT block, avg(o_totalprice) AS v FROM ({_BLOCK}) b GROUP BY block) m")
def _(spark, sf):
    df = table(spark, sf, "orders").select("o_orderkey", F.col("o_totalprice").alias("x0"))
    mean = blocks.sample_aggregate(df, ["x0"], lambda x, block: x.mean(0), 40, [0.0], [500000.0], None, SRC, "o_orderkey")
    return rounded(spark.createDataFrame([(float(mean[0]),)], "mean double"))


BLOCK_ROUNDS, RANGE_BINS = 6, 256


def _blocks(spark, sf, **options):
    df = D["D3"].points(spark, sf, ("o_orderkey",))
    return table_of(spark, blocks.block_average(df, names(2), 2, 1.0, df.count(), source=SRC, key="o_orderkey", max_iter=BLOCK_ROUNDS, range_bins=RANGE_BINS, **options).centroids)


def blocks_sql(ell: str, clip: bool = True, noise: bool = True, eps: float = 1.0, k: int = 2) -> str:
    """Two dimensions: blocks by key, starts from rows of the block, rounds, alignment by coordinates, clamped means, noise."""
    lo, hi = _bounds(clip)
    bounds = f"SELECT {', '.join(f'max({x}) FILTER (dim = {q}) AS {n}{q}' for q in (0, 1) for x, n in ((lo, 'lo'), (hi, 'hi')))} FROM r" if noise else "SELECT -1.0 AS lo0, 1.0 AS hi0, -1.0 AS lo1, 1.0 AS hi1"
    steps = [f"c0 AS MATERIALIZED (SELECT s.block, s.j, b.x0, b.x1 FROM (SELECT block, j, CAST(floor({SRC.uniform_sql('block-start', 'block', 'j')} * nb) AS BIGINT) AS pick FROM (SELECT block, count(*) AS nb FROM b GROUP BY 1) n, (SELECT range AS j FROM range({k})) q) s JOIN b ON s.block = b.block AND s.pick = b.place)"]
    for i in range(1, BLOCK_ROUNDS + 1):
        steps.append(f"a{i} AS MATERIALIZED (SELECT b.o_orderkey, b.block, b.x0, b.x1, arg_min(c.j, ((b.x0 - c.x0) * (b.x0 - c.x0) + (b.x1 - c.x1) * (b.x1 - c.x1), c.j)) AS j FROM b JOIN c{i - 1} c ON b.block = c.block GROUP BY ALL)")
        steps.append(f"c{i} AS MATERIALIZED (SELECT c.block, c.j, coalesce(m.x0, c.x0) AS x0, coalesce(m.x1, c.x1) AS x1 FROM c{i - 1} c LEFT JOIN (SELECT block, j, avg(x0) AS x0, avg(x1) AS x1 FROM a{i} GROUP BY 1, 2) m ON c.block = m.block AND c.j = m.j)")
    mean = ", ".join(f"(sum(least(greatest(x{q}, lo{q}), hi{q})) + (ell - count(*)) * least(greatest((lo{q} + hi{q}) / 2, lo{q}), hi{q})) / ell AS m{q}" for q in (0, 1))
    out = []
    for q in (0, 1):
        x = f"m{q}"
        if noise:
            x += f" + {SRC.laplace_sql(f'((hi{q} - lo{q}) * {2 * k} / (ell * {eps / 2!r}))', blocks.noise_step(0, eps / 2), 'CAST(ell AS BIGINT)', f'2 * j + {q}')}"
        out.append(R(f"least(1.0, greatest(-1.0, {x}))" if clip else x, f"x{q}"))
    ranges = f"{_range_cte(clip, eps / 2)},\n" if noise else ""
    return f"""WITH p AS MATERIALIZED ({D['D3'].points_sql('o_orderkey')}),
z AS (SELECT greatest(1, {ell}) AS ell FROM (SELECT count(*) AS n FROM p) t),
{ranges}w AS ({bounds}),
b AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY block ORDER BY x0, x1) - 1 AS place FROM (SELECT p.*, CAST(floor({SRC.uniform_sql('block', 'o_orderkey')} * ell) AS BIGINT) AS block FROM p, z) t),
{(',' + chr(10)).join(steps)},
o AS (SELECT block, row_number() OVER (PARTITION BY block ORDER BY x0, x1) - 1 AS j, x0, x1 FROM c{BLOCK_ROUNDS}),
m AS (SELECT j, ell, lo0, hi0, lo1, hi1, {mean} FROM o, z, w GROUP BY j, ell, lo0, hi0, lo1, hi1)
SELECT CAST(j AS INTEGER) AS j, {', '.join(out)} FROM m"""


_POWER, _3K = "floor(pow(n, 0.4) + 0.5)", "floor(n / 6.0 + 0.5)"
query("block_average", blocks_sql(_POWER))(lambda spark, sf: _blocks(spark, sf))
query("block_average_3k")(lambda spark, sf: _blocks(spark, sf, blocks="3k"))
query("block_average_unclipped", blocks_sql(_POWER, clip=False))(lambda spark, sf: _blocks(spark, sf, clip_range=False))
query("block_average_no_noise", blocks_sql(_POWER, noise=False))(lambda spark, sf: _blocks(spark, sf, noise=False))
query("block_size_sweep", f"SELECT name, a, CAST(greatest(1, floor(n / pow(n, a) + 0.5)) AS BIGINT) AS blocks FROM {_SHAPES}, (SELECT (range + 1) / 10.0 AS a FROM range(10)) e")(
    lambda spark, sf: spark.createDataFrame([(n, i / 10, em.block_count(N, ("size_exp", i / 10))) for n, N, *_ in shaped(spark, sf) for i in range(1, 11)], "name string, a double, blocks long")
)


def segment_means(spark, sf) -> DataFrame:
    """The mean customer of each market segment."""
    return D["D1"].points(spark, sf, ("c_mktsegment",)).groupBy("c_mktsegment").agg(F.avg("x0").alias("x0"), F.avg("x1").alias("x1"))


query("align_lexicographic", f"SELECT CAST(row_number() OVER (ORDER BY x0, x1) - 1 AS INTEGER) AS j, {R('x0')}, {R('x1')} FROM (SELECT avg(x0) AS x0, avg(x1) AS x1 FROM ({D['D1'].points_sql('c_mktsegment')}) p GROUP BY c_mktsegment) t")(
    lambda spark, sf: table_of(spark, blocks.align(np.array([[r["x0"], r["x1"]] for r in segment_means(spark, sf).collect()]), "lexicographic", None).tolist())
)
_CLAMP = f"SELECT round(sum(least(greatest(v, 100000), 200000)) / 40 + (40 - count(*)) * 150000.0 / 40, 6) AS mean FROM (SELECT block, max(o_totalprice) AS v FROM ({_BLOCK}) b GROUP BY block) m"


@query("block_clamp", _CLAMP)
def _(spark, sf):
    df = table(spark, sf, "orders").select("o_orderkey", F.col("o_totalprice").alias("x0"))
    mean = blocks.sample_aggregate(df, ["x0"], lambda x, block: x.max(0), 40, [100000.0], [200000.0], None, SRC, "o_orderkey")
    return rounded(spark.createDataFrame([(float(mean[0]),)], "mean double"))


query("block_align_anchor")(lambda spark, sf: _blocks(spark, sf, alignment="anchor"))
query("noise_on_best")(lambda spark, sf: table_of(spark, blocks.noise_only(C3, [2.0, 2.0], 48, 0.5, SRC)))
query("block_error_sources")(lambda spark, sf: ex.block_sizes(spark, D["D3"].points(spark, sf), 2, 2, 1.0, (0.2, 0.6, 0.9), QUICK))

# --- evolution ---------------------------------------------------------------------------------------

POOL = ev.init_pool(8, 2, 2, SRC)
_FIT = " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS cand, round(-sum(dist2), 6) AS fit FROM (SELECT {nearest_sql(names(2), p.reshape(2, 2).tolist())} FROM ({D['D3'].points_sql()}) p) q" for i, p in enumerate(POOL))
query("fitness_of_pool", _FIT)(lambda spark, sf: rounded(ev.fitness_of_pool(D["D3"].points(spark, sf), names(2), POOL, 2)))
query("init_pool", f"SELECT a.range AS cand, b.range AS i, round(2 * {SRC.uniform_sql('pool', 'a.range', 'b.range')} - 1, 6) AS v FROM range(8) a, range(4) b")(
    lambda spark, sf: rounded(spark.createDataFrame([(i, j, float(v)) for i, t in enumerate(POOL) for j, v in enumerate(t)], "cand long, i long, v double"))
)
_EV = values([(f"'{n}'", N) for n, N, *_ in PUBLISHED], "name, n")
query("evolve_rounds", f"SELECT name, e AS eps, CAST(greatest(8, floor(0.00125 * n * e / 10)) AS INTEGER) AS rounds FROM {_EV}, (VALUES (CAST(0.1 AS DOUBLE)), (CAST(1.0 AS DOUBLE)), (CAST(2.0 AS DOUBLE))) u(e)")(
    lambda spark, sf: spark.createDataFrame([(n, e, em.evolve_rounds(N, e)) for n, N, *_ in PUBLISHED for e in (0.1, 1.0, 2.0)], "name string, eps double, rounds int")
)
query("evolve_share", "SELECT CAST(1.0 / 80 AS DOUBLE) AS share")(lambda spark, sf: spark.createDataFrame([(em.evolve_share(1.0, 8),)], "share double"))


_PARENTS = ev.init_pool(3, 2, 2, NoiseSource("parents"))


def theta_sql(rows) -> str:
    return values([(i, f"[{', '.join(lit(v) for v in t)}]") for i, t in enumerate(rows)], "place, theta")


def offspring_sql(parents: str, m: int, n: int, dim: int, half: float, step: str) -> str:
    """Children (cand, theta) of parents (place, theta) of run 0."""
    u = lambda what, of: SRC.uniform_sql(f"{step}-{what}", "0", of)
    pair = "CAST(cand // 2 AS BIGINT)"
    child = "CASE WHEN cand % 2 = 0 THEN list_concat(a.theta[1:cut], b.theta[cut + 1:]) ELSE list_concat(b.theta[1:cut], a.theta[cut + 1:]) END"
    moved = f"list_transform(child, lambda v, i: CASE WHEN i - 1 = pos THEN greatest(-1.0, least(1.0, v + move)) ELSE v END)"
    made = f"SELECT range AS cand, CAST(floor({u('first', pair.replace('cand', 'range'))} * {m}) AS BIGINT) AS f, CAST(floor({u('second', pair.replace('cand', 'range'))} * {max(1, m - 1)}) AS BIGINT) AS s, 1 + CAST(floor({u('cut', pair.replace('cand', 'range'))} * {max(1, dim - 1)}) AS BIGINT) AS cut, CAST(floor({u('place', 'range')} * {dim}) AS BIGINT) AS pos, (2 * {u('move', 'range')} - 1) * {half!r} AS move FROM range({n})"
    return f"SELECT cand, {moved} AS theta FROM (SELECT cand, pos, move, {child} AS child FROM ({made}) k JOIN ({parents}) a ON a.place = f JOIN ({parents}) b ON b.place = (f + 1 + s) % {m}) w"


def _long(sql: str) -> str:
    return f"SELECT cand, CAST(i AS INTEGER) AS i, round(theta[i + 1], 6) AS v FROM ({sql}) t, (SELECT range AS i FROM range(4)) q"


_ORDER_PARENTS = f"SELECT o_orderkey % 3 AS place, [{', '.join(f'avg({x}) FILTER (o_orderkey % 2 = {j})' for j in (0, 1) for x in names(2))}] AS theta FROM ({D['D3'].points_sql('o_orderkey')}) p GROUP BY 1"


def order_parents(spark, sf) -> DataFrame:
    """Three parents: the mean orders with even and with odd keys, of every third key."""
    means = [F.avg(F.when(F.col("o_orderkey") % 2 == j, F.col(x))) for j in (0, 1) for x in names(2)]
    return D["D3"].points(spark, sf, ("o_orderkey",)).groupBy((F.col("o_orderkey") % 3).cast("int").alias("place")).agg(F.array(*means).alias("theta")).select(F.lit(0).cast("long").alias("run"), "place", "theta")


def _children(spark, half: float, step: str, parents: DataFrame | None = None) -> DataFrame:
    parents = parents if parents is not None else spark.createDataFrame([(0, i, [float(v) for v in t]) for i, t in enumerate(_PARENTS)], "run long, place int, theta array<double>")
    made = ev.offspring(parents, 3, 10, 4, half, SRC, step)
    return rounded(made.select(F.col("cand").cast("long").alias("cand"), F.posexplode("theta").alias("i", "v")))


query("crossover", _long(offspring_sql(_ORDER_PARENTS, 3, 10, 4, 0.0, "cross")))(lambda spark, sf: _children(spark, 0.0, "cross", order_parents(spark, sf)))
query("mutate", _long(offspring_sql(f"SELECT * FROM {theta_sql(_PARENTS)}", 3, 10, 4, 0.5, "mutate")))(lambda spark, sf: _children(spark, 0.5, "mutate"))


def evolve_sql(pool: int, keep: int, eps: float, private: bool) -> str:
    """Two rounds in two dimensions with two clusters."""
    sens, best = 4 * 2, "least({})".format(", ".join(f"(p.x0 - theta[{a}]) * (p.x0 - theta[{a}]) + (p.x1 - theta[{a + 1}]) * (p.x1 - theta[{a + 1}])" for a in (1, 3)))
    out = [f"p AS MATERIALIZED ({D['D3'].points_sql()})", f"g0 AS (SELECT place AS cand, theta FROM {theta_sql(ev.init_pool(pool, 2, 2, NoiseSource('pool-0')))})"]
    for g, (n, share) in enumerate(((keep, eps / (2 * keep)), (1, eps / 2))):
        rank = f"fit * {share / (2 * sens)!r} + {SRC.gumbel_sql(f'generation-{g}-{eps:.9g}', '0', 'cand')}" if private else "fit"
        out.append(f"f{g} AS MATERIALIZED (SELECT cand, any_value(theta) AS theta, -sum({best}) AS fit FROM p, g{g} GROUP BY cand)")
        out.append(f"k{g} AS MATERIALIZED (SELECT * FROM (SELECT row_number() OVER (ORDER BY {rank} DESC, cand) - 1 AS place, theta FROM f{g}) t WHERE place < {n})")
        if g == 0:
            out.append(f"g1 AS MATERIALIZED ({offspring_sql('SELECT * FROM k0', keep, pool, 4, 1.0, f'children-0-{eps:.9g}')})")
    return f"WITH {(',' + chr(10)).join(out)}\nSELECT CAST(j AS INTEGER) AS j, round(theta[2 * j + 1], 6) AS x0, round(theta[2 * j + 2], 6) AS x1 FROM k1, (SELECT range AS j FROM range(2)) q"


for _n, _private in (("evolve_two_rounds", True), ("evolve_nonprivate_two_rounds", False)):
    query(_n, evolve_sql(40, 10, 1.0, _private))(lambda spark, sf, private=_private: _evolved(spark, sf, rounds=2, private=private, n_pool=40))


def _evolved(spark, sf, n_pool: int = 200, **options):
    df = D["D3"].points(spark, sf)
    return table_of(spark, ev.evolve(df, names(2), 2, 1.0, df.count(), pool=n_pool, source=SRC, **options).centroids)


query("evolve")(lambda spark, sf: _evolved(spark, sf))
query("evolve_nonprivate")(lambda spark, sf: _evolved(spark, sf, private=False))
def _round_sweep(spark, sf):
    df = D["D3"].points(spark, sf)
    n = df.count()
    return spark.createDataFrame([(r, float(ev.evolve(df, names(2), 2, 1.0, n, rounds=r, source=SRC).trace[-1])) for r in (2, 4, 8, 16)], "rounds int, cost double")


query("evolve_round_sweep")(_round_sweep)


@query("evolve_many")
def _(spark, sf):
    df = D["D3"].points(spark, sf)
    return rounded(as_table(spark, [c.centroids for c in ev.evolve_many(df, names(2), 2, 1.0, df.count(), 5, pool=40, source=SRC)]).select("run", "j", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1")))


# --- synopses ----------------------------------------------------------------------------------------

GRIDS = {"2d": ("D3", g.GridSpec((39, 39))), "3d": ("D4", g.GridSpec((12, 12, 12))), "6d": ("D5", g.GridSpec((4,) * 6))}


def _cells_sql(key: str, spec: g.GridSpec) -> str:
    return f"SELECT {g.cell_id_sql(spec)} AS cell, count(*) AS n_exact FROM ({D[key].points_sql()}) p GROUP BY 1"


for _n, (_key, _spec) in GRIDS.items():
    query(f"grid_counts_{_n}", _cells_sql(_key, _spec))(lambda spark, sf, w=D[_key], s=_spec: g.cell_counts(w.points(spark, sf), w.cols, s))


def release_sql(key: str, spec: g.GridSpec, eps: float, run: int = 0) -> str:
    return f"SELECT e.range AS cell, coalesce(n_exact, 0) + {SRC.laplace_sql(repr(1 / eps), g.noise_step(run, eps), 'e.range')} AS n, {g.cell_center_sql('e.range', spec)} FROM range({spec.cells}) e LEFT JOIN ({_cells_sql(key, spec)}) h ON e.range = h.cell"


def _release(spark, sf, key="D3", spec=GRIDS["2d"][1], eps=1.0):
    w = D[key]
    return g.release_grid(w.points(spark, sf), w.cols, eps, spec=spec, source=SRC)


S2 = GRIDS["2d"][1]
query("grid_cell_id", f"SELECT {_all(['x0', 'x1'])}, {g.cell_id_sql(S2)} AS cell FROM ({D['D3'].points_sql()}) p")(lambda spark, sf: rounded(D["D3"].points(spark, sf).withColumn("cell", g.cell_id(names(2), S2))))
query("grid_all_cells", f"SELECT e.range AS cell, coalesce(n_exact, 0) AS n_exact FROM range({S2.cells}) e LEFT JOIN ({_cells_sql('D3', S2)}) h ON e.range = h.cell")(lambda spark, sf: g.all_cells(D["D3"].points(spark, sf), names(2), S2))
query("grid_release_2d", f"SELECT cell, {R('n')}, {_all(['x0', 'x1'])} FROM ({release_sql('D3', S2, 1.0)}) r")(lambda spark, sf: rounded(_release(spark, sf).cells))
query("grid_release_3d", f"SELECT cell, {R('n')}, {_all(names(3))} FROM ({release_sql('D4', GRIDS['3d'][1], 0.5)}) r")(lambda spark, sf: rounded(_release(spark, sf, "D4", GRIDS["3d"][1], 0.5).cells))
query("grid_centers", f"SELECT e.range AS cell, {', '.join('round(' + x.replace(' AS ', ', 6) AS ') for x in g.cell_center_sql('e.range', GRIDS['3d'][1]).split(', '))} FROM range({GRIDS['3d'][1].cells}) e")(
    lambda spark, sf: rounded(spark.range(GRIDS["3d"][1].cells).select(F.col("id").alias("cell"), *g.cell_center("id", GRIDS["3d"][1])))
)
_TEN = " UNION ALL ".join(f"SELECT {i} AS run, e.range AS cell, coalesce(n_exact, 0) + {SRC.laplace_sql('1.0', 'grids', str(i), 'e.range')} AS n FROM range(100) e LEFT JOIN ({_cells_sql('D3', g.GridSpec((10, 10)))}) h ON e.range = h.cell" for i in range(10))
query("grid_release_10", f"SELECT run, cell, {R('n')} FROM ({_TEN}) r")(lambda spark, sf: rounded(g.release_many(D["D3"].points(spark, sf), names(2), 1.0, g.GridSpec((10, 10)), 10, SRC).select("run", "cell", "n")))
query("grid_geometric")(lambda spark, sf: g.all_cells(D["D3"].points(spark, sf), names(2), S2).select("cell", (F.col("n_exact") + SRC.geometric(1.0, "geometric", "cell")).alias("n")))
query("grid_size_2d", f"SELECT name, round(n * 0.5 / 10, 6) AS cells FROM {_NT}")(lambda spark, sf: rounded(spark.createDataFrame([(n, g.cells_2d(N, 0.5)) for n, N, *_ in PUBLISHED], "name string, cells double")))


@query("grid_size_table", "SELECT CAST(d.range + 1 AS INTEGER) AS d, e AS eps, round(pow(60000 * e / 10, 2.0 * (d.range + 1) / (3.0 + d.range)), 3) AS cells FROM range(10) d, (VALUES (CAST(0.05 AS DOUBLE)), (CAST(0.5 AS DOUBLE)), (CAST(1.0 AS DOUBLE))) u(e)")
def _(spark, sf):
    return spark.createDataFrame([(d, e, g.cells_general(60000, e, d)) for d in range(1, 11) for e in (0.05, 0.5, 1.0)], "d int, eps double, cells double").withColumn("cells", F.round("cells", 3))


for _n, _sqln in (("raw", "n"), ("round_nonneg", "greatest(0.0, floor(n + 0.5))"), ("clip_zero", "greatest(n, 0.0)")):
    _src = f"SELECT {_sqln} AS n, x0, x1 FROM ({release_sql('D3', S2, 1.0)}) rel"
    _nm = {"raw": "grid_lloyd_step", "round_nonneg": "grid_round_nonneg", "clip_zero": "grid_clip_zero"}[_n]
    _q = rounds_sql(_src, C3, 1, weight="n", r=1.0, least=1e-9)
    _q = _q.replace("sum(n) AS n", "sum(n) AS n")
    query(_nm, _q)(lambda spark, sf, how=_n: table_of(spark, lloyd(_release(spark, sf).weighted(how), names(2), C3, 1, weight="n", r=1.0).centroids))
query("grid_round_replicate", f"SELECT cell, CAST(greatest(0, floor(n + 0.5)) AS BIGINT) AS copies FROM ({release_sql('D3', S2, 1.0)}) r WHERE greatest(0, floor(n + 0.5)) > 0")(lambda spark, sf: _release(spark, sf).replicated().groupBy("cell").agg(F.count("*").alias("copies")))
query("synopsis_nicv", f"SELECT round(sum(n * dist2) / sum(n), 6) AS nicv FROM (SELECT n, {nearest_sql(names(2), C3)} FROM ({release_sql('D3', S2, 1.0)}) r) q")(lambda spark, sf: rounded(spark.createDataFrame([(synopsis_nicv(_release(spark, sf).cells, names(2), C3),)], "nicv double")))


def grid_cte(eps: float, tag: str = "g", theta: float = 10.0, run: int = 0) -> str:
    """{tag}(id, n, x0, x1): the synopsis of points p in two dimensions, whose size follows the number of rows."""
    cell = "(" + " * m + ".join(f"greatest(0, least(CAST(floor((x{i} + 1.0) / 2.0 * m) AS BIGINT), m - 1))" for i in (0, 1)) + ")"
    return f"""{tag}z AS (SELECT greatest(1, CAST(floor(sqrt(greatest(1.0, count(*) * {eps!r} / {theta!r})) + 0.5) AS BIGINT)) AS m FROM p),
{tag}h AS (SELECT {cell} AS cell, count(*) AS c FROM p, {tag}z GROUP BY 1),
{tag} AS MATERIALIZED (SELECT e.cell AS id, coalesce(c, 0) + {SRC.laplace_sql(repr(1 / eps), g.noise_step(run, eps), 'e.cell')} AS n, 2.0 * ((e.cell // m) % m + 0.5) / m - 1.0 AS x0, 2.0 * (e.cell % m + 0.5) / m - 1.0 AS x1 FROM (SELECT unnest(range(m * m)) AS cell, m FROM {tag}z) e LEFT JOIN {tag}h h ON e.cell = h.cell)"""


ROUNDS = 100


def grid_kmeans_ctes(eps: float, sets, tag: str = "g") -> str:
    """{tag}best (j, x0, x1): the start whose outcome is best on the synopsis."""
    steps = family_ctes(tag, sets, ROUNDS, "n", 1.0, 1e-9, tag=tag)
    cost = _nicv_cte(f"{tag}c{ROUNDS}", 2, f"{tag}v", "n", tag)
    return f"{grid_cte(eps, tag)},\n{steps},\n{cost},\n{tag}best AS MATERIALIZED (SELECT j, x0, x1 FROM {tag}c{ROUNDS} WHERE run = (SELECT run FROM {tag}v ORDER BY round(v, 9), run LIMIT 1))"


def grid_kmeans_sql(eps: float, sets) -> str:
    return f"WITH {_P(D['D3'].points_sql())},\n{grid_kmeans_ctes(eps, sets)}\nSELECT CAST(j AS INTEGER) AS j, {_all(names(2))} FROM gbest"


def _grid(spark, sf, inits):
    df = D["D3"].points(spark, sf)
    return table_of(spark, grid_kmeans(df, names(2), 2, 1.0, df.count(), inits, source=SRC).centroids)


query("grid_kmeans_1init", grid_kmeans_sql(1.0, [C3]))(lambda spark, sf: _grid(spark, sf, [C3]))
query("grid_select_init", grid_kmeans_sql(1.0, S30))(lambda spark, sf: _grid(spark, sf, 30))
query("grid_theta_sweep")(lambda spark, sf: ex.theta_sweep(spark, ex.stand_ins(spark, sf, ["D3"]), 1.0, QUICK))
query("grid_degenerate", "SELECT CAST(1 AS BIGINT) AS cells, CAST(true AS BOOLEAN) AS alike")(
    lambda spark, sf: (lambda s: spark.createDataFrame([(s.cells, s.m == (1,) * 64)], "cells long, alike boolean"))(g.grid_spec(g.cells_general(500, 0.1, 64), 64))
)
query("cluster_shape_cells", f"SELECT cluster, count(*) AS cells, round(sum(n), 6) AS n FROM (SELECT n, {nearest_sql(names(2), C3)} FROM ({release_sql('D3', S2, 1.0)}) r) q GROUP BY cluster")(lambda spark, sf: rounded(assign(_release(spark, sf).cells, names(2), C3).groupBy("cluster").agg(F.count("*").alias("cells"), F.sum("n").alias("n"))))
query("synthesize_points")(lambda spark, sf: g.synthesize(_release(spark, sf), 5000, SRC))


@query("synopsis_roundtrip", f"SELECT cell, {R('n')}, {_all(['x0', 'x1'])} FROM ({release_sql('D3', S2, 1.0)}) r")
def _(spark, sf):
    import uuid

    from dpcluster.sources.io import shared_folder

    path = f"{shared_folder(spark)}/synopsis-{uuid.uuid4().hex}"
    _release(spark, sf).save(path)
    return rounded(g.Synopsis.load(spark, path).cells)


def boxes_sql(d: int, n: int) -> str:
    rows = []
    src = NoiseSource("boxes")
    for q in range(n):
        ends = [sorted((2 * src.draw("a", q, i) - 1, 2 * src.draw("b", q, i) - 1)) for i in range(d)]
        rows.append((q, *(repr(round(v, 6)) for e in ends for v in e)))
    return values(rows, "qid, " + ", ".join(f"lo{i}, hi{i}" for i in range(d)))


_IN = "x0 >= lo0 AND x0 < hi0 AND x1 >= lo1 AND x1 < hi1"
_EXACT = f"SELECT qid, coalesce(c, 0) AS n FROM (SELECT qid FROM {boxes_sql(2, 40)}) b LEFT JOIN (SELECT qid AS q, count(*) AS c FROM {boxes_sql(2, 40)}, ({D['D3'].points_sql()}) p WHERE {_IN} GROUP BY qid) g ON qid = q"
query("range_count_exact", _EXACT)(lambda spark, sf: g.range_count_exact(D["D3"].points(spark, sf), names(2), g.fixed_boxes(spark, 2, 40)))
query("range_count_bucketed", _EXACT)(lambda spark, sf: g.range_count_bucketed(D["D3"].points(spark, sf), names(2), g.fixed_boxes(spark, 2, 40)))
_HALF = 1 / 39
_PART = " * ".join(f"greatest(0.0, least(x{i} + {_HALF!r}, hi{i}) - greatest(x{i} - {_HALF!r}, lo{i})) / {2 / 39!r}" for i in range(2))
query("range_count_est", f"SELECT qid, round(sum(n * {_PART}), 6) AS est FROM {boxes_sql(2, 40)}, ({release_sql('D3', S2, 1.0)}) r WHERE {' AND '.join(f'x{i} + {_HALF!r} > lo{i} AND x{i} - {_HALF!r} < hi{i}' for i in range(2))} GROUP BY qid")(
    lambda spark, sf: rounded(g.range_count(_release(spark, sf), g.fixed_boxes(spark, 2, 40)))
)

# --- planner -----------------------------------------------------------------------------------------

query("eps_threshold_table", f"SELECT name, CAST(rho AS DOUBLE) AS rho, round({em.epsilon_threshold_sql()}, 6) AS eps_star FROM {_SHAPES}, (VALUES (0.0), (0.25), (0.5)) r(rho)")(
    lambda spark, sf: rounded(spark.createDataFrame([(n, rho, em.epsilon_threshold(N, d, k, rho=rho)) for n, N, d, k in shaped(spark, sf) for rho in (0.0, 0.25, 0.5)], "name string, rho double, eps_star double"))
)
query("two_stage_conditions", f"SELECT name, e AS eps, e >= {em.epsilon_threshold_sql(rho='0.25')} AS refine FROM {_NT}, (VALUES (CAST(0.05 AS DOUBLE)), (CAST(0.3 AS DOUBLE)), (CAST(2.0 AS DOUBLE))) u(e)")(
    lambda spark, sf: spark.createDataFrame([(n, e, decide(N, d, k, e).path == "grid+refine") for n, N, d, k in PUBLISHED for e in (0.05, 0.3, 2.0)], "name string, eps double, refine boolean")
)


def _two(spark, sf, key="D3", **options):
    w = D[key]
    df = w.points(spark, sf)
    return two_stage(df, w.cols, w.k, options.pop("eps", 1.0), df.count(), source=SRC, **options)


def two_stage_sql(eps: float, split: float = 0.5, rounds: int = 1, force: str | None = None) -> str:
    """Both ways of the planner on D3 (two dimensions, two clusters), and its choice by the threshold."""
    first, rest = split * eps, (eps - split * eps) / rounds
    noisy = family_ctes("p", S30[:1], rounds, r=1.0, noise=lambda i, c: SRC.laplace_sql(repr(3.0 / rest), f"{noise_step(0, i, 3.0 / rest)}-{c}", "c.j"), tag="r")
    refine = f"{grid_kmeans_ctes(first, S30, 'h')},\nrc0 AS (SELECT 0 AS run, * FROM hbest),\n" + noisy.split("\n", 1)[1]
    pays = "true" if force == "refine" else f"{eps!r} >= (SELECT {em.epsilon_threshold_sql(n='count(*)', d='2', k='2', rho='0.25')} FROM p)"
    grid = "" if force == "refine" else f"{grid_kmeans_ctes(eps, S30)},\n"
    whole = "" if force == "refine" else f" UNION ALL SELECT j, x0, x1 FROM gbest WHERE NOT {pays}"
    return f"WITH {_P(D['D3'].points_sql())},\n{grid}{refine}\nSELECT CAST(j AS INTEGER) AS j, {_all(names(2))} FROM (SELECT j, x0, x1 FROM rc{rounds} WHERE {pays}{whole}) t"


query("two_stage_entry", two_stage_sql(1.0))(lambda spark, sf: table_of(spark, _two(spark, sf).centroids))
query("two_stage_refine", two_stage_sql(2.0))(lambda spark, sf: table_of(spark, _two(spark, sf, eps=2.0).centroids))
query("two_stage_fallback", two_stage_sql(0.01))(lambda spark, sf: table_of(spark, _two(spark, sf, eps=0.01).centroids))
query("two_stage_forced", two_stage_sql(0.05, force="refine"))(lambda spark, sf: table_of(spark, _two(spark, sf, eps=0.05, force="refine").centroids))
query("two_stage_rounds", two_stage_sql(1.0, rounds=2, force="refine"))(lambda spark, sf: table_of(spark, _two(spark, sf, refine_rounds=2, force="refine").centroids))


@query("two_stage_many")
def _(spark, sf):
    df = D["D3"].points(spark, sf)
    sets = two_stage_many(df, names(2), 2, 1.0, df.count(), source=SRC)
    return rounded(as_table(spark, sets).select("run", "j", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1")))


query("two_stage_split_sweep")(lambda spark, sf: spark.createDataFrame([(s, *map(float, _two(spark, sf, split=s, force="refine").centroids[0])) for s in (0.3, 0.5, 0.7)], "split double, x0 double, x1 double"))
# the refining round in SQL, from the centroids of a first stage that both engines know
query("two_stage_refine_round", rounds_sql(D["D3"].points_sql(), C3, 1, [3 / 0.5], r=1.0))(lambda spark, sf: table_of(spark, noisy_lloyd(D["D3"].points(spark, sf), names(2), 2, 0.5, 1, init=C3, source=SRC).centroids))


@query("tune_k_on_synopsis")
def _(spark, sf):
    syn = _release(spark, sf)
    syn.cells = syn.cells.persist()
    ks = (1, 2, 3, 4)
    _, scores = tune_on_synopsis(syn, ks, lambda s, k: cluster_synopsis(s, init_sets(3, k, 2))[1])
    return spark.createDataFrame([(k, float(v)) for k, v in zip(ks, scores)], "k int, nicv double")


# --- error models ------------------------------------------------------------------------------------

_E = "(VALUES (CAST(0.1 AS DOUBLE)), (CAST(1.0 AS DOUBLE))) u(e)"
_M14 = "2.0 * d * (1 + 0.25) * pow(k * {t} * (d + 1.0) / (n * {e}), 2)"
_CELLS = "pow(n * e / 10.0, 2.0 * d / (2.0 + d))"


def model(name: str, sql: str, fn, given: bool = False) -> None:
    """given: at the sizes of the given tables instead of the published ones."""
    query(name, f"SELECT name, e AS eps, round(ln({sql}), 6) AS log_value FROM {_SHAPES if given else _NT}, {_E}")(
        lambda spark, sf: rounded(spark.createDataFrame([(n, e, fn(N, d, k, e)) for n, N, d, k in (shaped(spark, sf) if given else PUBLISHED) for e in (0.1, 1.0)], "name string, eps double, v double").select("name", "eps", F.log("v").alias("log_value")))
    )


model("mse_noisy_lloyd_table", _M14.format(t=5, e="e"), lambda n, d, k, e: em.mse_noisy_lloyd(n, d, k, e, 5))
model("mse_two_stage_table", _M14.format(t=1, e="(e / 2)"), em.mse_two_stage)
model("var_grid_table", "2.0 * d * 1000 * pow(k, (d - 2.0) / d) / (3.0 * n * n * e * e)", lambda n, d, k, e: em.var_grid(n, d, k, e, 1000))
model("var_grid_plugged_table", f"2.0 * d * {_CELLS} * pow(k, (d - 2.0) / d) / (3.0 * n * n * e * e)", em.var_grid_plugged)
model("bias2_grid_table", f"d / pow({_CELLS}, 2.0 / d)", lambda n, d, k, e: em.bias2_grid_bound(d, g.cells_general(n, e, d)), given=True)
model("range_mse_model", f"0.3 * 2 * {_CELLS} / (e * e) + 2.0 * d * pow(0.05 * n / pow({_CELLS}, 1.0 / d), 2)", lambda n, d, k, e: em.range_mse(0.3, 0.05, g.cells_general(n, e, d), n, d, e))
model("centroid_mse_delta", "(2.0 / (e * e)) / pow(n / k, 2) + pow(0.25 * n / k, 2) * (2.0 / (e * e)) / pow(n / k, 4)".replace("n / k", "n * 1.0 / k"), lambda n, d, k, e: em.centroid_mse_delta(0.25 * n / k, n / k, 2 / e**2, 2 / e**2), given=True)


@query("scaling_report", f"SELECT d, k, round(avg(ln({_M14.format(t=5, e='e')})), 6) AS noisy, round(avg(ln(2.0 * d * {_CELLS} * pow(k, (d - 2.0) / d) / (3.0 * n * n * e * e))), 6) AS grid FROM (SELECT 10000 AS n, CAST(a.range + 2 AS INTEGER) AS d, CAST(b.range + 2 AS INTEGER) AS k, e FROM range(9) a, range(9) b, {_E}) t GROUP BY CUBE (d, k)")
def _(spark, sf):
    rows = [(d, k, em.mse_noisy_lloyd(10000, d, k, e, 5), em.var_grid_plugged(10000, d, k, e)) for d in range(2, 11) for k in range(2, 11) for e in (0.1, 1.0)]
    return rounded(spark.createDataFrame(rows, "d int, k int, a double, b double").cube("d", "k").agg(F.avg(F.log("a")).alias("noisy"), F.avg(F.log("b")).alias("grid")))


@query("grid_size_argmin", "SELECT CAST(range + 2 AS INTEGER) AS d, true AS least FROM range(9)")
def _(spark, sf):
    alpha = 0.5
    rows = []
    for d in range(2, 11):
        beta = (alpha / 2) ** 0.5 / 10  # theta is 10
        best, n = g.cells_general(50000, 0.5, d), 50000
        rows.append((d, all(em.range_mse(alpha, beta, best, n, d, 0.5) <= em.range_mse(alpha, beta, best * f, n, d, 0.5) for f in (0.9, 1.1))))
    return spark.createDataFrame(rows, "d int, least boolean")


# --- measures ----------------------------------------------------------------------------------------

_Q = f"(SELECT *, {nearest_sql(names(2), C3)} FROM ({D['D3'].points_sql()}) p) q"
query("nicv_nearest", f"SELECT round(avg(dist2), 6) AS nicv FROM {_Q}")(lambda spark, sf: rounded(assign(D["D3"].points(spark, sf), names(2), C3).agg(F.avg("dist2").alias("nicv"))))
query("nicv_assigned", f"SELECT round(sum(dist2) / count(*), 6) AS nicv, count(DISTINCT cluster) AS clusters FROM {_Q}")(lambda spark, sf: rounded(assign(D["D3"].points(spark, sf), names(2), C3).agg((F.sum("dist2") / F.count("*")).alias("nicv"), F.countDistinct("cluster").alias("clusters"))))
query("nicv_many", " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS run, round(avg(dist2), 6) AS nicv FROM (SELECT {nearest_sql(names(2), c)} FROM ({D['D3'].points_sql()}) p) q" for i, c in enumerate(PAIR)))(
    lambda spark, sf: rounded(family_sums(D["D3"].points(spark, sf), names(2), PAIR).groupBy("run").agg((F.sum("cost") / F.sum("n")).alias("nicv")))
)
query("cluster_size_skew", f"SELECT max(n) AS largest, min(n) AS smallest FROM (SELECT cluster, count(*) AS n FROM {_Q} GROUP BY cluster) t")(lambda spark, sf: assign(D["D3"].points(spark, sf), names(2), C3).groupBy("cluster").agg(F.count("*").alias("n")).agg(F.max("n").alias("largest"), F.min("n").alias("smallest")))
_RUNS = [("'D1'", "'baseline'", lit(0), lit(0.5)), ("'D1'", "'a'", lit(1), lit(0.75)), ("'D1'", "'a'", lit(1), lit(1.0)), ("'D1'", "'b'", lit(1), lit(0.625))]


def _runs(spark):
    return spark.createDataFrame([("D1", "baseline", 0.0, 0.5), ("D1", "a", 1.0, 0.75), ("D1", "a", 1.0, 1.0), ("D1", "b", 1.0, 0.625)], "dataset string, method string, eps double, nicv double")


query("summary_by_method", f"SELECT dataset, method, eps, round(avg(nicv), 6) AS nicv, round(stddev_samp(nicv), 6) AS sd, round(stddev_samp(nicv) / sqrt(count(*)), 6) AS se, count(*) AS runs FROM {values(_RUNS, 'dataset, method, eps, nicv')} GROUP BY 1, 2, 3")(lambda spark, sf: rounded(metrics.summarize(_runs(spark))))
query("nicv_gap", f"SELECT method, nicv - 0.5 AS gap FROM {values(_RUNS, 'dataset, method, eps, nicv')} WHERE method <> 'baseline'")(lambda spark, sf: metrics.nicv_gap(_runs(spark)).select("method", "gap"))
query("mse_decomposition", f"SELECT round(avg(e * e), 6) AS mse, round(var_pop(e), 6) AS variance, round(avg(e) * avg(e), 6) AS bias2 FROM (SELECT n - coalesce(n_exact, 0) AS e FROM ({release_sql('D3', S2, 1.0)}) r LEFT JOIN ({_cells_sql('D3', S2)}) h ON r.cell = h.cell) t")(
    lambda spark, sf: rounded(metrics.mse_parts(_release(spark, sf).cells.join(g.all_cells(D["D3"].points(spark, sf), names(2), S2), "cell"), "n", "n_exact"))
)
query("grid_bias_exact", f"SELECT cluster, round(avg(-1 + 2 * (floor((x0 + 1) / 2 * 39) + 0.5) / 39 - x0), 6) AS bias0 FROM (SELECT *, {nearest_sql(names(2), C3)} FROM ({D['D3'].points_sql()}) p WHERE x0 < 1) q GROUP BY cluster")(
    lambda spark, sf: rounded(assign(D["D3"].points(spark, sf).where("x0 < 1"), names(2), C3).withColumn("t", F.element_at(F.array(*g.cell_center(g.cell_id(names(2), S2), S2)), 1)).groupBy("cluster").agg(F.avg(F.col("t") - F.col("x0")).alias("bias0")))
)
C7 = uniform_init(4, 10, "embeddings", 0.5)
_PUR = f"SELECT round(sum(n) * 1.0 / sum(total), 6) AS purity FROM (SELECT max(n) AS n, sum(n) AS total FROM (SELECT cluster, label, count(*) AS n FROM (SELECT label, {nearest_sql(names(10), C7)} FROM ({D['D7'].points_sql('label')}) p) q GROUP BY 1, 2) t GROUP BY cluster) u"
query("purity_embeddings", _PUR)(lambda spark, sf: rounded(metrics.purity(assign(D["D7"].points(spark, sf, ("label",)), names(10), C7))))


@query("centroid_mse_empirical", f"WITH p AS (SELECT o_orderkey AS id, x0 FROM ({D['D3'].points_sql('o_orderkey')}) q), t AS (SELECT sum(x0) AS s, count(*) AS c FROM p) SELECT round(ln(avg(pow((s + {SRC.laplace_sql('2.0', 'sum-0', 'id')}) / (c + {SRC.laplace_sql('2.0', 'count', 'id')}) - s / c, 2))), 6) AS log_mse FROM p, t")
def _(spark, sf):
    """Of the mean price of orders, with one draw for the key of each order."""
    df = D["D3"].points(spark, sf, ("o_orderkey",)).withColumnRenamed("o_orderkey", "id")
    total = df.agg(F.sum("x0").alias("s"), F.count("*").alias("c")).first()
    return metrics.centroid_mse_empirical(df, [total["s"]], total["c"], 2.0, source=SRC).select(F.round(F.log("mse"), 6).alias("log_mse"))


query("convergence_trace")(lambda spark, sf: ex.convergence(spark, D["D4"].points(spark, sf), 3, 3, 30, 12))
@query("iters_to_baseline")
def _(spark, sf):
    """Rounds until 1% above the best of thirty runs."""
    df = grouped(D["D4"].points(spark, sf), names(3), "__rows").persist()
    return metrics.iterations_to(ex.convergence(spark, df, 3, 3, 30, 12), best_of(df, names(3), init_sets(30, 3, 3), weight="__rows")[1])



query("run_stats")(lambda spark, sf: (lambda c: spark.createDataFrame([(c.path, c.stats["scans"], c.ledger.spent, c.decision.explain())], "path string, scans int, spent double, decision string"))(_two(spark, sf)))

# --- generated data and experiments ------------------------------------------------------------------

query("gaussian_clusters", f"SELECT id, cluster, {_all(names(3))} FROM ({gaussian_clusters_sql(2000, 3, 4)}) q")(lambda spark, sf: rounded(gaussian_clusters(spark, 2000, 3, 4)))
query("exp_compare_small")(lambda spark, sf: metrics.summarize(ex.compare(spark, ex.stand_ins(spark, sf, ["D3"]), [0.1, 1.0], ("noisy_lloyd", "block_average", "block_3k", "grid_kmeans"), QUICK)))
query("exp_hybrid_small")(lambda spark, sf: metrics.summarize(ex.compare(spark, ex.stand_ins(spark, sf, ["D3"]), [0.1, 1.0], ("noisy_lloyd", "grid_kmeans", "two_stage"), QUICK)))
query("exp_heatmap_small")(lambda spark, sf: ex.heatmap(ex.compare(spark, ex.generated(spark, (2, 4), (2, 4), 2000), [1.0], ("noisy_lloyd", "grid_kmeans"), QUICK), (2, 4)))
query("exp_hybrid_heatmap")(lambda spark, sf: ex.heatmap(ex.compare(spark, ex.generated(spark, (2,), (2, 3), 2000), [1.0], ("grid_kmeans", "two_stage"), QUICK), (2, 3)))
query("exp_runtime")(lambda spark, sf: metrics.summarize(ex.compare(spark, ex.stand_ins(spark, sf, ["D3"]), [0.1], ("noisy_lloyd", "grid_kmeans"), QUICK)))
query("exp_range_mse")(lambda spark, sf: ex.range_accuracy(spark, D["D3"].points(spark, sf), 2, 1.0, (2, 8, 39, 120), 20))
query("exp_count_bias")(lambda spark, sf: ex.count_bias(spark, (0.2, 1.0), 2, 3000))
query("exp_scale_n")(lambda spark, sf: ex.size_scaling(spark, [sf], "D3", 0.5, QUICK))


@query("exp_init")
def _(spark, sf):
    df, out = gaussian_clusters(spark, 2000, 4, 8, seed=3).select(*names(4)).persist(), []
    for kind in ("uniform", "packed"):
        sets = noisy_lloyd_many(df, names(4), init_sets(6, 8, 4, 5, kind), 2, 1.0, source=SRC)
        out.append((kind, sum(nicv_many(df, names(4), sets)) / len(sets)))
    return spark.createDataFrame(out, "init string, nicv double")


@query("exp_range_fix")
def _(spark, sf):
    df = gaussian_clusters(spark, 3000, 2, 3).select(*names(2)).persist()
    found = [(e, c, blocks.block_average(df, names(2), 3, e, 3000, clip_range=c, source=SRC).centroids) for e in (0.1, 1.0) for c in (True, False)]
    return spark.createDataFrame([(e, c, v) for (e, c, _), v in zip(found, nicv_many(df, names(2), [x for *_, x in found]))], "eps double, clipped boolean, nicv double")
