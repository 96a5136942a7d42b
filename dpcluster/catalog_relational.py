"""Queries of the relational helpers around the methods: reading, shaping, joining, aggregating, windows, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dpcluster.catalog import query, rounded
from dpcluster.catalog_methods import C3, D, SRC, S2, _A, _P, _cells_sql, _release, family_ctes, grid_kmeans_sql, lit, nearest_sql, release_sql
from dpcluster.functions.domain import names
from dpcluster.operators import grid as g
from dpcluster.operators.centroids import as_table
from dpcluster.operators.lloyd import assign, lloyd
from dpcluster.sources.io import round_trip
from dpcluster.sources.workloads import hash_sample, table
from dpcluster.streaming import windows as sw

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "labels")


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def _(spark, sf):
    out = None
    for t in TABLES:
        one = table(spark, sf, t).agg(F.lit(t).alias("name"), F.count("*").alias("n"))
        out = one if out is None else out.unionAll(one)
    return out


_CUST = "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer"
for _kind in ("csv", "json", "orc", "parquet"):
    query(f"roundtrip_{_kind}", _CUST)(lambda spark, sf, kind=_kind: round_trip(table(spark, sf, "customer"), kind))


@query("sql_entry_grid", f"SELECT cell, count(*) AS n FROM (SELECT {g.cell_id_sql(S2)} AS cell FROM ({D['D3'].points_sql()}) p) q GROUP BY cell")
def _(spark, sf):
    from dpcluster.functions.sql import register

    register(spark)
    D["D3"].points(spark, sf).createOrReplaceTempView("points_d3")
    return spark.sql("SELECT cast(grid_cell(x0, 39) * 39 + grid_cell(x1, 39) AS bigint) AS cell, count(*) AS n FROM points_d3 GROUP BY 1")


def simple(name: str, sql: str, f) -> None:
    query(name, sql)(lambda spark, sf: f(lambda t: table(spark, sf, t)))


simple("project_features", "SELECT l_orderkey, CAST(l_linenumber AS DOUBLE) AS line, l_quantity * 2 AS twice FROM lineitem", lambda t: t("lineitem").select("l_orderkey", F.col("l_linenumber").cast("double").alias("line"), (F.col("l_quantity") * 2).alias("twice")))
simple("filter_box", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderdate >= DATE '1996-01-01'", lambda t: t("orders").where(F.col("o_totalprice").between(1000, 200000) & (F.col("o_orderdate") >= F.lit("1996-01-01").cast("date"))).select("o_orderkey"))
simple("filter_predicates", "SELECT c_custkey FROM customer WHERE (c_mktsegment LIKE '%U%' OR c_nationkey IN (1, 2, 3)) AND c_acctbal IS NOT NULL AND NOT (c_custkey < 10)", lambda t: t("customer").where((F.col("c_mktsegment").like("%U%") | F.col("c_nationkey").isin(1, 2, 3)) & F.col("c_acctbal").isNotNull() & ~(F.col("c_custkey") < 10)).select("c_custkey"))
simple("dedupe_locations", "SELECT DISTINCT user_id, event_type FROM events", lambda t: t("events").dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type"))
simple("hash_sample", "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE CAST(('0x' || substr(md5(concat_ws('|', CAST(l_orderkey AS VARCHAR), CAST(l_partkey AS VARCHAR))), 1, 8)) AS BIGINT) % 100 < 5", lambda t: hash_sample(t("lineitem"), 5, "l_orderkey", "l_partkey").select("l_orderkey", "l_linenumber", "l_partkey"))
simple("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", lambda t: t("customer").select(F.col("c_nationkey").alias("k")).unionAll(t("supplier").select("s_nationkey")).distinct())
simple("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier", lambda t: t("customer").select(F.col("c_nationkey").alias("k")).intersect(t("supplier").select("s_nationkey")))
simple("set_except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier", lambda t: t("nation").select(F.col("n_nationkey").alias("k")).subtract(t("supplier").select("s_nationkey")))
simple("set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier", lambda t: t("customer").select(F.col("c_nationkey").alias("k")).intersectAll(t("supplier").select("s_nationkey")))
simple("set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier", lambda t: t("customer").select(F.col("c_nationkey").alias("k")).exceptAll(t("supplier").select("s_nationkey")))
query("topk_cells", f"SELECT cell, round(n, 6) AS n FROM ({release_sql('D3', S2, 1.0)}) r ORDER BY n DESC, cell LIMIT 20")(lambda spark, sf: rounded(_release(spark, sf).cells.orderBy(F.desc("n"), "cell").limit(20).select("cell", "n")))
simple("topk_candidates", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5", lambda t: t("customer").orderBy(F.desc("c_acctbal"), "c_custkey").offset(5).limit(10).select("c_custkey", "c_acctbal"))


@query("topk_cells_per_cluster", f"SELECT j, cell, round(n, 6) AS n FROM (SELECT x0 > 0 AS j, cell, n, row_number() OVER (PARTITION BY x0 > 0 ORDER BY n DESC, cell) AS i FROM ({release_sql('D3', S2, 1.0)}) r) t WHERE i <= 3")
def _(spark, sf):
    w = Window.partitionBy("j").orderBy(F.desc("n"), "cell")
    return rounded(_release(spark, sf).cells.withColumn("j", F.col("x0") > 0).withColumn("i", F.row_number().over(w)).where("i <= 3").select("j", "cell", "n"))


simple("pivot_heatmap", "SELECT c_nationkey, count(*) FILTER (WHERE c_mktsegment = 'BUILDING') AS building, count(*) FILTER (WHERE c_mktsegment = 'MACHINERY') AS machinery FROM customer GROUP BY 1", lambda t: t("customer").groupBy("c_nationkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).agg(F.count("c_custkey")).select("c_nationkey", F.coalesce("BUILDING", F.lit(0)).alias("building"), F.coalesce("MACHINERY", F.lit(0)).alias("machinery")))
simple("unpivot_dims", "SELECT p_partkey, 'p_size' AS dim, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part", lambda t: t("part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice").unpivot("p_partkey", ["p_size", "p_retailprice"], "dim", "v"))

# --- joins -------------------------------------------------------------------------------------------

simple("star_join_features", "SELECT l_orderkey, l_linenumber, l_partkey, o_totalprice, c_acctbal, p_size FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey", lambda t: t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_linenumber", "l_partkey", "o_totalprice", "c_acctbal", "p_size"))
_J = "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 6) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
for _name, _hint in (("join_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    simple(_name, _J, lambda t, h=_hint: rounded(t("lineitem").join(t("orders").hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))))
simple("labels_left", "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id", lambda t: t("documents").select("doc_id").join(t("labels"), "doc_id", "left").select("doc_id", "quality"))
_TWO = f"SELECT coalesce(a.cell, b.cell) AS cell, coalesce(a.n, 0) AS a, coalesce(b.n, 0) AS b FROM (SELECT cell, n_exact AS n FROM ({_cells_sql('D3', g.GridSpec((10, 10)))}) q WHERE cell % 2 = 0) a {{}} JOIN (SELECT cell, n_exact AS n FROM ({_cells_sql('D3', g.GridSpec((10, 10)))}) q WHERE cell % 3 = 0) b ON a.cell = b.cell"


def _two(spark, sf, how):
    c = g.cell_counts(D["D3"].points(spark, sf), names(2), g.GridSpec((10, 10))).withColumnRenamed("n_exact", "n")
    a, b = c.where("cell % 2 = 0").withColumnRenamed("n", "a"), c.where("cell % 3 = 0").withColumnRenamed("n", "b")
    return a.join(b, "cell", how).select("cell", F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"))


query("grid_diff_full", _TWO.format("FULL"))(lambda spark, sf: _two(spark, sf, "full"))
query("grid_diff_right", _TWO.format("RIGHT"))(lambda spark, sf: _two(spark, sf, "right"))
_SEMI = f"SELECT range AS cell FROM range({S2.cells}) WHERE range {{}} (SELECT cell FROM ({_cells_sql('D3', S2)}) q)"
for _name, _how, _in in (("cells_semi", "left_semi", "IN"), ("cells_anti", "left_anti", "NOT IN")):
    query(_name, _SEMI.format(_in))(lambda spark, sf, how=_how: spark.range(S2.cells).withColumnRenamed("id", "cell").join(g.cell_counts(D["D3"].points(spark, sf), names(2), S2), "cell", how))
simple("interval_join_windows", "SELECT d, count(*) AS n FROM (SELECT CAST(range AS INTEGER) AS d FROM range(30)) w JOIN events ON ts >= TIMESTAMP '2024-01-01' + d * INTERVAL 1 DAY AND ts < TIMESTAMP '2024-01-01' + (d + 1) * INTERVAL 1 DAY GROUP BY d", lambda t: t("events").groupBy(F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("d")).agg(F.count("*").alias("n")).where("d between 0 and 29"))


@query("asof_release", "SELECT event_id, max(w) AS w FROM events JOIN (SELECT CAST(range * 7 AS INTEGER) AS w FROM range(5)) r ON date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) >= w GROUP BY event_id")
def _(spark, sf):
    """The latest of weekly releases before each event.

    Releases are few: their days are one sorted array beside every event, and nothing is shuffled or sorted by time."""
    day = F.datediff("ts", F.lit("2024-01-01").cast("date"))
    releases = spark.range(5).select((F.col("id") * 7).cast("int").alias("at")).agg(F.sort_array(F.collect_list("at")).alias("at"))
    return table(spark, sf, "events").select("event_id", day.alias("day")).join(F.broadcast(releases)).select("event_id", F.array_max(F.filter("at", lambda x: x <= F.col("day"))).alias("w")).where("w is not null")


_MEANS_SQL = f"(SELECT o_orderpriority AS run, o_orderstatus AS j, avg(x0) AS x0, avg(x1) AS x1 FROM ({D['D3'].points_sql('o_orderpriority, o_orderstatus')}) p GROUP BY 1, 2)"


def order_means(spark, sf) -> DataFrame:
    """(run, j, c): the mean order of each status, for each priority."""
    df = D["D3"].points(spark, sf, ("o_orderpriority", "o_orderstatus"))
    return df.groupBy(F.col("o_orderpriority").alias("run"), F.col("o_orderstatus").alias("j")).agg(F.array(F.avg("x0"), F.avg("x1")).alias("c"))


@query("centroid_pairs", f"SELECT a.run AS run, round(sqrt(pow(a.x0 - b.x0, 2) + pow(a.x1 - b.x1, 2)), 6) AS apart FROM {_MEANS_SQL} a JOIN {_MEANS_SQL} b ON a.run = b.run AND a.j < b.j")
def _(spark, sf):
    """How far the centroids of a run are from each other: a self join within the run."""
    c = order_means(spark, sf)
    apart = F.sqrt(F.aggregate(F.zip_with("a.c", "b.c", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return rounded(c.alias("a").join(c.alias("b"), (F.col("a.run") == F.col("b.run")) & (F.col("a.j") < F.col("b.j"))).select(F.col("a.run").alias("run"), apart.alias("apart")))


# --- aggregates and windows --------------------------------------------------------------------------

query("centroids_as_arrays", f"SELECT run, string_agg(j || ':' || round(x0, 3) || ':' || round(x1, 3), ',' ORDER BY j) AS cs FROM {_MEANS_SQL} t GROUP BY run")(
    lambda spark, sf: order_means(spark, sf).groupBy("run").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("j", "c"))), lambda x: F.concat_ws(":", x["j"], F.round(x["c"][0], 3), F.round(x["c"][1], 3))), ",").alias("cs"))  # k centroids a run
)
query("nonempty_cells", f"SELECT count(DISTINCT cell) AS n FROM ({_cells_sql('D3', S2)}) q")(lambda spark, sf: D["D3"].points(spark, sf).agg(F.countDistinct(g.cell_id(names(2), S2)).alias("n")))
query("capacity_estimates")(lambda spark, sf: table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median")))
simple("profile_columns", "SELECT round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(var_samp(l_tax), 6) AS v, round(corr(l_quantity, l_extendedprice), 6) AS c FROM lineitem", lambda t: rounded(t("lineitem").agg(F.percentile("l_quantity", F.lit(0.25)).alias("q1"), F.var_samp("l_tax").alias("v"), F.corr("l_quantity", "l_extendedprice").alias("c"))))
def _bins():
    return [F.least(F.floor(F.col(f"x{i}") * 4 + 4), F.lit(7)).alias(f"g{i}") for i in range(3)]

_GSQL = f"(SELECT {', '.join(f'least(CAST(floor(x{i} * 4 + 4) AS BIGINT), 7) AS g{i}' for i in range(3))} FROM ({D['D4'].points_sql()}) p) q"
query("grid_marginals_cube", f"SELECT g0, g1, g2, count(*) AS n FROM {_GSQL} GROUP BY CUBE (g0, g1, g2)")(lambda spark, sf: D["D4"].points(spark, sf).select(*_bins()).cube("g0", "g1", "g2").agg(F.count("*").alias("n")))
simple("summary_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(grouping(l_returnflag) AS INTEGER) AS a, CAST(grouping(l_linestatus) AS INTEGER) AS b FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)", lambda t: t("lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping("l_returnflag").cast("int").alias("a"), F.grouping("l_linestatus").cast("int").alias("b")))


@query("summary_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
def _(spark, sf):
    table(spark, sf, "customer").createOrReplaceTempView("customer_v")
    return spark.sql("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer_v GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")


query("negative_cells", f"SELECT count(*) FILTER (WHERE n < 0) AS negative, round(sum(n) FILTER (WHERE n < 0), 6) AS total FROM ({release_sql('D3', S2, 1.0)}) r")(lambda spark, sf: rounded(_release(spark, sf).cells.agg(F.count_if(F.col("n") < 0).alias("negative"), F.sum(F.when(F.col("n") < 0, F.col("n"))).alias("total"))))
def _ranks():
    return Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")

simple("rank_candidates", "SELECT c_custkey, CAST(row_number() OVER w AS INTEGER) AS i, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS d, round(percent_rank() OVER w, 6) AS p, CAST(ntile(4) OVER w AS INTEGER) AS t FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)", lambda t: rounded(t("customer").select("c_custkey", F.row_number().over(_ranks()).alias("i"), F.rank().over(_ranks()).alias("r"), F.dense_rank().over(_ranks()).alias("d"), F.percent_rank().over(_ranks()).alias("p"), F.ntile(4).over(_ranks()).alias("t"))))
def _user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")

_MOVES = f"WITH {_P(D['D3'].points_sql())}, {family_ctes('p', [C3], 3)}, t AS (" + " UNION ALL ".join(f"SELECT {i} AS i, j, x0, x1 FROM fc{i}" for i in range(4)) + ") SELECT CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, round(sqrt(pow(x0 - lag(x0) OVER w, 2) + pow(x1 - lag(x1) OVER w, 2)), 6) AS back, round(first_value(x0) OVER w, 6) AS first, round(lead(x0) OVER w, 6) AS next FROM t WINDOW w AS (PARTITION BY j ORDER BY i)"


@query("centroid_moves", _MOVES)
def _(spark, sf):
    """How far each centroid moves from round to round."""
    trace = lloyd(D["D3"].points(spark, sf), names(2), C3, 3, 0.0).trace
    t = as_table(spark, trace, "i").select(F.col("i").cast("int").alias("i"), "j", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1"))
    w = Window.partitionBy("j").orderBy("i")
    back = F.sqrt(F.pow(F.col("x0") - F.lag("x0").over(w), 2) + F.pow(F.col("x1") - F.lag("x1").over(w), 2))
    return rounded(t.select("i", "j", back.alias("back"), F.first("x0").over(w).alias("first"), F.lead("x0").over(w).alias("next")))




@query("hist_cumulative", "SELECT bin, sum(n) OVER (ORDER BY bin) AS upto FROM (SELECT CAST(floor(l_quantity) AS BIGINT) AS bin, count(*) AS n FROM lineitem GROUP BY 1) h")
def _(spark, sf):
    h = table(spark, sf, "lineitem").groupBy(F.floor("l_quantity").alias("bin")).agg(F.count("*").alias("n"))
    return h.select("bin", F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))


simple("window_rows_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS v FROM events", lambda t: rounded(t("events").select("event_id", F.avg("value").over(_user().rowsBetween(-2, 2)).alias("v"))))
simple("window_range_sum", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY d RANGE BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS v FROM (SELECT *, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS d FROM events) e", lambda t: rounded(t("events").withColumn("d", F.datediff("ts", F.lit("2024-01-01").cast("date"))).select("event_id", F.sum("value").over(Window.partitionBy("user_id").orderBy("d").rangeBetween(-3, 0)).alias("v"))))

# --- functions ---------------------------------------------------------------------------------------

simple("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, round(sqrt(l_quantity) + ln(1 + l_tax) + pow(l_discount, 2) + exp(-l_tax) + sign(l_tax - 0.04) + l_partkey % 7, 6) AS v FROM lineitem", lambda t: rounded(t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", (F.sqrt("l_quantity") + F.log1p("l_tax") + F.pow("l_discount", F.lit(2)) + F.exp(-F.col("l_tax")) + F.signum(F.col("l_tax") - 0.04) + F.pmod("l_partkey", F.lit(7))).alias("v"))))
simple("fn_date_features", "SELECT event_id, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS d, CAST(hour(ts) AS INTEGER) AS h, CAST(minute(ts) AS INTEGER) AS m, CAST(dayofmonth(ts) AS INTEGER) AS dom FROM events", lambda t: t("events").select("event_id", F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("d"), F.hour("ts").alias("h"), F.minute("ts").alias("m"), F.dayofmonth("ts").alias("dom")))
simple("fn_text_features", "SELECT doc_id, length(text) AS n, length(text) - length(replace(text, ' ', '')) AS spaces, upper(substr(source, 1, 3)) AS s, trim(lang) || '-' || lower(source) AS tag FROM documents", lambda t: t("documents").select("doc_id", F.length("text").cast("long").alias("n"), (F.length("text") - F.length(F.replace("text", F.lit(" "), F.lit("")))).cast("long").alias("spaces"), F.upper(F.substring("source", 1, 3)).alias("s"), F.concat(F.trim("lang"), F.lit("-"), F.lower("source")).alias("tag")))
simple("fn_json_feature", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", lambda t: t("events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
simple("fn_vector_distance", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE) - 0.1) * (CAST(x AS DOUBLE) - 0.1)))), 6) AS d FROM embeddings", lambda t: rounded(t("embeddings").select("vec_id", F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + (x.cast("double") - 0.1) * (x.cast("double") - 0.1))).alias("d"))))
simple("explode_embedding", "SELECT vec_id, CAST(i AS INTEGER) AS i, round(CAST(list_extract(embedding, i + 1) AS DOUBLE), 6) AS v FROM embeddings, (SELECT range AS i FROM range(64)) r", lambda t: rounded(t("embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v")).withColumn("v", F.col("v").cast("double"))))
simple("fn_map_counts", "SELECT event_id, CASE event_type " + " ".join(f"WHEN '{t}' THEN {i}" for i, t in enumerate(("click", "view", "purchase"))) + " ELSE -1 END AS code FROM events", lambda t: t("events").select("event_id", F.coalesce(F.element_at(F.create_map(*(F.lit(x) for i, t_ in enumerate(("click", "view", "purchase")) for x in (t_, i))), F.col("event_type")), F.lit(-1)).alias("code")))
simple("fn_null_rules", "SELECT d.doc_id, coalesce(nullif(quality, 0), -1) AS q, CASE WHEN toxic IS NULL THEN 'none' WHEN toxic = 1 THEN 'yes' ELSE 'no' END AS t FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id", lambda t: t("documents").select("doc_id").join(t("labels"), "doc_id", "left").select("doc_id", F.coalesce(F.nullif("quality", F.lit(0)), F.lit(-1)).alias("q"), F.when(F.col("toxic").isNull(), "none").when(F.col("toxic") == 1, "yes").otherwise("no").alias("t")))
simple("sum_fixed_point", "SELECT l_returnflag, sum(CAST(floor(l_extendedprice * 1000000 + 0.5) AS BIGINT)) AS total FROM lineitem GROUP BY 1", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.sum(F.floor(F.col("l_extendedprice") * 1000000 + 0.5).cast("decimal(38,0)")).alias("total")))

# --- windows of events (batch twins of the streams) --------------------------------------------------

_EV = f"(SELECT event_id, ts, user_id, {D['D2'].points_sql().split('FROM')[0].removeprefix('SELECT ')} FROM (SELECT *, CAST(hour(ts) * 3600 + minute(ts) * 60 + second(ts) AS DOUBLE) AS f0, value AS f1 FROM events) r) p"
_W5 = g.GridSpec((5, 5))
query("window_tumbling_grid", f"SELECT CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS day, {g.cell_id_sql(_W5)} AS cell, count(*) AS n FROM {_EV} GROUP BY 1, 2")(
    lambda spark, sf: sw.window_counts(sw.points(table(spark, sf, "events")), _W5).select(F.datediff("start", F.lit("2024-01-01").cast("date")).alias("day"), "cell", "n")
)
query("window_sliding_grid", f"SELECT CAST(day - s AS INTEGER) AS day, cell, count(*) AS n FROM (SELECT date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS day, {g.cell_id_sql(_W5)} AS cell FROM {_EV}) q, (VALUES (0), (1)) o(s) GROUP BY 1, 2")(
    lambda spark, sf: sw.window_counts(sw.points(table(spark, sf, "events")), _W5, "2 days", "1 day").select(F.datediff("start", F.lit("2024-01-01").cast("date")).alias("day"), "cell", "n")
)
query("window_session", "SELECT user_id, count(*) AS sessions, sum(n) AS n FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events) a) b GROUP BY 1, 2) c GROUP BY 1")(
    lambda spark, sf: sw.sessions(table(spark, sf, "events")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))
)
query("window_release")(lambda spark, sf: sw.release_windows(sw.window_counts(sw.points(table(spark, sf, "events")), _W5), _W5, 1.0, SRC))


@query("udtf_grid_cells", f"SELECT range AS cell, {', '.join('round(' + x.replace(' AS ', ', 6) AS ') for x in g.cell_center_sql('range', g.GridSpec((4, 4))).split(', '))} FROM range(16) e")
def _(spark, sf):
    from dpcluster.functions.sql import register

    register(spark)
    return spark.sql("SELECT cell, round(centre[0], 6) AS x0, round(centre[1], 6) AS x1 FROM grid_cells(4, 2)")


_EST = grid_kmeans_sql(1.0, [C3])
_EST = _EST[: _EST.rindex("\nSELECT")]


@query("estimator", f"{_EST}, est AS (SELECT p.id, arg_min(c.j, ((p.x0 - c.x0) * (p.x0 - c.x0) + (p.x1 - c.x1) * (p.x1 - c.x1), c.j)) AS j FROM p, gbest c GROUP BY p.id) SELECT CAST(j AS INTEGER) AS cluster, count(*) AS n FROM est GROUP BY 1")
def _(spark, sf):
    """fit and transform: sizes of the clusters of a fitted model."""
    from dpcluster.operators.estimator import PrivateKMeans

    df = D["D3"].points(spark, sf)
    model = PrivateKMeans("grid_kmeans", 2, 1.0, options={"source": SRC, "inits": [C3]}).fit(df, names(2))
    return model.transform(df).groupBy("cluster").agg(F.count("*").alias("n"))


@query("result_store", f"WITH {_P(D['D3'].points_sql())}, {family_ctes('p', [C3], 2)} SELECT CAST(j AS INTEGER) AS j, round(x0, 6) AS x0, round(x1, 6) AS x1 FROM fc2")
def _(spark, sf):
    """Centroids written and read back."""
    import uuid

    from dpcluster.sources.io import load_centroids, save_centroids, shared_folder

    path = f"{shared_folder(spark)}/centroids-{uuid.uuid4().hex}"
    save_centroids(spark, path, lloyd(D["D3"].points(spark, sf), names(2), C3, 2, 0.0).centroids)
    return rounded(load_centroids(spark, path).select("j", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1")))


@query("text_lines", "SELECT count(*) AS n FROM customer")
def _(spark, sf):
    """Text written and read back, a row a line."""
    return round_trip(table(spark, sf, "customer").select(F.concat_ws("|", "c_custkey", "c_name").alias("value")), "text").agg(F.count("*").alias("n"))


@query("stratified_sample", "SELECT c_custkey, c_mktsegment FROM customer WHERE CAST(('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 8)) AS BIGINT) % 100 < CASE c_mktsegment WHEN 'BUILDING' THEN 50 ELSE 10 END")
def _(spark, sf):
    from dpcluster.sources.workloads import stratified_sample

    return stratified_sample(table(spark, sf, "customer"), "c_mktsegment", {"BUILDING": 50}, 10, "c_custkey").select("c_custkey", "c_mktsegment")


_NEAR = f"SELECT o_orderkey, cluster FROM (SELECT *, {nearest_sql(names(2), C3)} FROM ({D['D3'].points_sql('o_orderkey')}) p) q"


@query("nearest_vectorized", _NEAR)
def _(spark, sf):
    from dpcluster.functions.sql import nearest_udf

    return D["D3"].points(spark, sf, ("o_orderkey",)).select("o_orderkey", nearest_udf(C3)("x0", "x1").alias("cluster"))


@query("sql_nearest", _NEAR)
def _(spark, sf):
    from dpcluster.functions.sql import register

    register(spark)
    D["D3"].points(spark, sf, ("o_orderkey",)).createOrReplaceTempView("keyed_d3")
    c = ", ".join(f"array({', '.join(f'{x!r}D' for x in p)})" for p in C3)
    return spark.sql(f"SELECT o_orderkey, nearest2(array(x0, x1), array({c})) AS cluster FROM keyed_d3")


@query("weighted_centroid", f"SELECT cluster, round(sum(w * x0) / sum(w), 6) AS x0, round(sum(w * x1) / sum(w), 6) AS x1 FROM (SELECT x0, x1, 1 + abs(x1) AS w, {nearest_sql(names(2), C3)} FROM ({D['D3'].points_sql()}) p) q GROUP BY cluster")
def _(spark, sf):
    from dpcluster.functions.sql import weighted_centroid

    df = assign(D["D3"].points(spark, sf).withColumn("w", 1 + F.abs("x1")), names(2), C3)
    return rounded(df.groupBy("cluster").agg(weighted_centroid(names(2), "w").alias("c")).select("cluster", F.col("c")[0].alias("x0"), F.col("c")[1].alias("x1")))


__all__ = ["assign", "lit"]
