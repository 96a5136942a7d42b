"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Sources share a budget of words by weight; no source may exceed ``limit`` times its size, and what
is cut off goes to the others by weight.  A document is taken once for every complete epoch of its
source.  The fraction that is left goes to documents in rising order of an exponential key divided
by their quality weight, by prefix sums, until the word budget is met exactly: the last document is
taken in part.

The keys of a source are spread over buckets between quantiles of its keys, whose number follows the
number of rows, so that only sums cross between tasks; a source that holds most rows is spread like any
other, whatever the weights.  Keys come from a hash of the id, so reruns agree.

Defined results: null text has size 0; a null source is a source of its own; repeated rows count
each on their own; a null quality is the least there is; a source without words has target 0; extra
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dpcluster.llm.scratch import Scratch

WORDS = r"[^\x20\x09-\x0D]+"
LIMIT = 3.0
LEAST_QUALITY = 1e-6
#: Bounds of buckets of one source are an array beside its rows: 64 kB at most.
MAX_BUCKETS = 8_192
WEIGHTS = (1, 2, 3)


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def source_targets(sizes: list[tuple[str | None, int]], weights=WEIGHTS, share: float = 1.0, limit: float = LIMIT) -> list[tuple[str | None, int, float]]:
    """Targets of sources in order: the budget by weight, capped at limit times the size."""
    order = sorted(sizes, key=lambda x: (x[0] is None, x[0] or ""))
    left, target = float(share * sum(s for _, s in order)), [0.0] * len(order)
    free = list(range(len(order)))
    weight = [float(weights[i % len(weights)]) for i in free]
    while free:
        total = sum(weight[i] for i in free)
        over = [i for i in free if left * weight[i] / total > limit * order[i][1]]
        if not over:
            for i in free:
                target[i] = left * weight[i] / total
            break
        for i in over:
            target[i] = limit * order[i][1]
        left = max(0.0, left - sum(target[i] for i in over))
        free = [i for i in free if i not in set(over)]
    return [(name, size, t) for (name, size), t in zip(order, target)]


def mix(docs: DataFrame, weights=WEIGHTS, share: float = 1.0, limit: float = LIMIT, quality: Column | None = None, seed: int = 17, bucket_rows: int = 50_000, row: Column | None = None) -> DataFrame:
    """Per document: doc_id, size, source_size, target, taken, epochs and fraction.

    quality: a positive weight of a document; larger ones are likelier in the fractional part.
    row: a value that is carried along as ``row``.
    The names of sources are gathered on the driver (a few bytes a source), never documents.
    """
    spark, tables = docs.sparkSession, Scratch(docs.sparkSession, "mix")
    even = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("doc_id")), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
    good = F.greatest(F.coalesce(quality.cast("double"), F.lit(0.0)), F.lit(LEAST_QUALITY)) if quality is not None else F.lit(1.0)
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words(F.col("text")).alias("size"), (-F.log(even) / good).alias("key"), (row if row is not None else F.lit(None).cast("long")).alias("row"))
    keyed = tables.write(sized, "keyed")
    # as many bounds of buckets as the largest source needs
    largest = keyed.groupBy("source").count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0]
    buckets = max(1, min(MAX_BUCKETS, -(-largest // bucket_rows)))
    if buckets > 1:
        cuts = [(i + 1) / buckets for i in range(buckets - 1)]
        bounds = keyed.groupBy(F.col("source").alias("s")).agg(F.array_sort(F.percentile_approx("key", cuts, 20 * buckets)).alias("bounds"))
        placed = keyed.join(F.broadcast(bounds), F.col("s").eqNullSafe(F.col("source"))).withColumn("bucket", F.size(F.filter("bounds", lambda b: b < F.col("key"))))
        sized = tables.write(placed.drop("s", "bounds"), "sized")
    else:
        sized = keyed.withColumn("bucket", F.lit(0))
    sums = tables.write(sized.groupBy("source", "bucket").agg(F.sum("size").alias("words")), "sums")
    by_source = [(r["source"], r["words"]) for r in sums.groupBy("source").agg(F.sum("words").alias("words")).collect()]
    targets = spark.createDataFrame(
        [(s, n, t, int(t // n) if n else 0, max(0, round(t - n * (t // n))) if n else 0) for s, n, t in source_targets(by_source, weights, share, limit)],
        "source string, source_size long, target double, epochs long, part long",
    )
    ahead = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.withColumn("before", F.coalesce(F.sum("words").over(ahead), F.lit(0)))
    plan = starts.withColumnRenamed("source", "s").join(targets, F.col("s").eqNullSafe(F.col("source"))).select("source", "bucket", "before", "source_size", "target", "epochs", "part")
    inside = Window.partitionBy("source", "bucket").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    ranked = sized.withColumn("ahead", F.coalesce(F.sum("size").over(inside), F.lit(0))).withColumnsRenamed({"source": "s", "bucket": "b"})
    joined = ranked.join(plan, F.col("s").eqNullSafe(F.col("source")) & (F.col("b") == F.col("bucket")))
    fraction = F.greatest(F.lit(0), F.least(F.col("size"), F.col("part") - F.col("before") - F.col("ahead")))
    return joined.select("doc_id", "size", "source_size", "target", (F.col("epochs") * F.col("size") + fraction).cast("long").alias("taken"), "epochs", fraction.cast("long").alias("fraction"), F.col("source"), *(["row"] if row is not None else []))


def copies(docs: DataFrame, **options) -> DataFrame:
    """The mix as documents: each row once for every complete epoch, once more if half of it or more is in the fraction.

    Rows are told apart by id, text and source; rows that agree in all of these come as often as the luckiest of them."""
    row = F.xxhash64(F.col("doc_id").cast("long"), "text", F.col("source").cast("string"))
    taken = mix(docs, row=row, **options).groupBy("row").agg(F.max(F.col("epochs") + F.when((F.col("fraction") > 0) & (2 * F.col("fraction") >= F.col("size")), 1).otherwise(0)).cast("int").alias("__times"))
    times = docs.withColumn("__row", row).join(taken.withColumnRenamed("row", "__mixed"), F.col("__row") == F.col("__mixed")).where("__times > 0")
    return times.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__times")))).select(*docs.columns)
