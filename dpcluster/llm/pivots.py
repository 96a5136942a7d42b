"""Exact top-k inner products by pivot-table elimination.

Distances of every row to the pivots are computed once and travel with the row.  For a query, the
largest difference of its distances and a row's is a lower bound of their distance, hence with the
norms an upper bound of their inner product.  A query starts with the k-th best score among a
bounded sample of the rows; rows whose bound is below it are never evaluated, the others in the
order of the bound until no bound left reaches the k-th best score.  Rows and queries meet in blocks
of bounded size, dealt by place in the input, so that equal vectors or hot ids do not gather.

Pivots are spread-out rows of a bounded sample; they change the work, never the result.

Defined results: rows without an id take no part; a query's candidates are the rows with other ids;
a repeated query id is searched once, with its least vector; repeated rows are candidates each;
vectors of a length other than the most common one take no part; components beyond a long
become its least or greatest value, and sums beyond a long are those of 64-bit arithmetic, which
wrap: a block of rows where that can happen is evaluated whole, without bounds.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpcluster.llm import scratch
from dpcluster.llm.scratch import Scratch
from dpcluster.llm.vectors import best, matrix, usable

ROW_BLOCK, QUERY_BLOCK, PIVOTS, SAMPLE = 32_768, 512, 24, 2_000
STEP, MARGIN = 6, 1e-6
LEAST = -(2**63)


def quantised(vector: Column, scale: int = 64) -> Column:
    return F.transform(vector, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")))


def spread_pivots(sample: np.ndarray, n: int) -> np.ndarray:
    """Rows far from each other, chosen one by one."""
    if not len(sample):
        return sample
    sample = np.unique(sample, axis=0).astype(np.float64)
    chosen = [0]
    far = ((sample - sample[0]) ** 2).sum(1)
    while len(chosen) < min(n, len(sample)):
        chosen.append(int(far.argmax()))
        far = np.minimum(far, ((sample - sample[chosen[-1]]) ** 2).sum(1))
    return sample[chosen]


def distances(x: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """Of each row to each pivot, in single precision; the margins of the bounds cover the rounding."""
    x = x.astype(np.float64)
    return np.sqrt(np.maximum((x * x).sum(1)[:, None] + (pivots * pivots).sum(1)[None] - 2 * x @ pivots.T, 0)).astype(np.float32)


class Products:
    """Inner products of queries and rows in 64-bit integers; ``exact`` where none can pass a long."""

    def __init__(self, q: np.ndarray, x: np.ndarray):
        top = [float(np.abs(v.astype(np.float64)).max(initial=0)) for v in (q, x)]
        size = max(1.0, q.shape[1] * top[0] * top[1])
        kind = np.float32 if size < 2**24 else np.float64 if size < 2**53 else np.int64  # whichever is exact
        self.qs, self.xs, self.exact = q.astype(kind, copy=False), x.astype(kind, copy=False), size < 2**62

    def of(self, i: int, rows: np.ndarray) -> np.ndarray:
        few = 6 * len(rows) < len(self.xs)  # gathering rows costs more than a product
        return (self.xs[rows] @ self.qs[i] if few else (self.xs @ self.qs[i])[rows]).astype(np.int64)


def first_thresholds(q: np.ndarray, q_ids: np.ndarray, x: np.ndarray, x_ids: np.ndarray, k: int) -> np.ndarray:
    """For each query the k-th best score among some of its candidates: no lower score is in the answer."""
    out = np.full(len(q), LEAST, np.int64)
    if len(q) and len(x) > k:
        scores_of = Products(q, x)
        for i in range(len(q)):
            scores = scores_of.of(i, np.flatnonzero(x_ids != q_ids[i]))
            if len(scores) >= k:
                out[i] = np.partition(scores, len(scores) - k)[len(scores) - k]
    return out


def search_block(q: np.ndarray, q_ids: np.ndarray, dq: np.ndarray, least: np.ndarray, x: np.ndarray, x_ids: np.ndarray, dx: np.ndarray, sizes: np.ndarray, k: int, first: int = 256):
    """Top k of each query among the rows: (query ids, row ids, scores), and how many products were taken.

    dq, dx: distances to the pivots, sizes: the pivots' norms; least: scores below which nothing counts."""
    scores_of, dx = Products(q, x), np.ascontiguousarray(dx.T)
    x2, q2 = (x.astype(np.float64) ** 2).sum(1), (q.astype(np.float64) ** 2).sum(1)
    x_margin, out, taken = (MARGIN * np.sqrt(x2)).astype(np.float32), [], 0
    for i in range(len(q)):
        ceiling = (q2[i] + x2) * (0.5 + 1e-9) + 1 if scores_of.exact else np.full(len(x), np.inf)
        margins = (MARGIN * (sizes + np.sqrt(q2[i]))).astype(np.float32)
        open_rows, low, other = np.arange(len(x)), np.zeros(len(x), np.float32), x_ids != q_ids[i]
        bound, gap = ceiling, np.empty(len(x), np.float32)
        for p in range(0, len(dx), STEP):  # some pivots at a time, each on the rows that the ones before have left
            whole = 2 * len(open_rows) > len(x)
            for j in range(p, min(p + STEP, len(dx))):
                if whole:
                    np.subtract(dx[j], dq[i, j], out=gap)
                else:
                    gap = dx[j][open_rows] - dq[i, j]
                np.abs(gap, out=gap)
                gap -= margins[j]
                np.maximum(low, gap, out=low)
            if whole:
                bound = ceiling - np.square(np.maximum(low - x_margin, 0), dtype=np.float64) / 2
                open_rows = np.flatnonzero((bound >= float(least[i])) & other)
                if 2 * len(open_rows) <= len(x) or p + STEP >= len(dx):
                    bound, low = bound[open_rows], low[open_rows]
            else:
                bound = ceiling[open_rows] - np.square(np.maximum(low - x_margin[open_rows], 0), dtype=np.float64) / 2
                keep = bound >= float(least[i])
                open_rows, low, bound = open_rows[keep], low[keep], bound[keep]
        ids, scores, step, floor = np.zeros(0, np.int64), np.zeros(0, np.int64), first, least[i]
        while len(open_rows):
            now = open_rows
            if len(now) > step:
                part = np.argpartition(-bound, step - 1)
                now, open_rows, bound = open_rows[part[:step]], open_rows[part[step:]], bound[part[step:]]
            else:
                open_rows = open_rows[:0]
            taken += len(now)
            new = scores_of.of(i, now)
            good = new >= floor
            ids, scores = np.concatenate([ids, x_ids[now[good]]]), np.concatenate([scores, new[good]])
            if len(scores) >= k:
                floor = max(floor, np.partition(scores, len(scores) - k)[len(scores) - k])
                good = scores >= floor
                ids, scores = ids[good], scores[good]
                good = np.lexsort((ids, ~scores))[:k]
                ids, scores = ids[good], scores[good]
                keep = bound >= float(floor)
                if len(open_rows) and not keep.all():
                    open_rows, bound = open_rows[keep], bound[keep]
            step *= 4
        out.append((np.full(len(ids), q_ids[i]), ids, scores))
    return tuple(np.concatenate(c) for c in zip(*out)) if out else (np.zeros(0, np.int64),) * 3, taken


def search(rows: DataFrame, queries: DataFrame, k: int, pivots: int = PIVOTS, row_block: int = ROW_BLOCK, query_block: int = QUERY_BLOCK) -> DataFrame:
    """rows and queries: vec_id long, v array<long>. Returns query_id, rank, vec_id, score."""
    spark, tables = rows.sparkSession, Scratch(rows.sparkSession, "pivots")
    scratch.share_code(spark)
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), "v").where("vec_id is not null")
    length = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    length, dims = (length["n"], length["count"]) if length else (1, 0)
    rows = rows.where(F.size("v") == length)
    asked = queries.select(F.col("vec_id").cast("long").alias("query_id"), "v").where((F.col("query_id").isNotNull()) & (F.size("v") == length)).groupBy("query_id").agg(F.min("v").alias("v"))
    sample = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("vec_id", "v").toArrow()
    known, known_ids = matrix(sample.column("v"), np.int64), sample.column("vec_id").to_numpy()
    chosen = spread_pivots(known, pivots)
    sizes = np.sqrt((chosen * chosen).sum(1)) if len(chosen) else np.zeros(0)

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Adds the distances to the pivots, once for each row, and the first threshold of a query."""
        for batch in batches:
            if len(batch):
                v = matrix(batch.column("v"), np.int64)
                batch = batch.append_column("d", pa.FixedSizeListArray.from_arrays(pa.array(distances(v, chosen).ravel()), len(chosen)).cast(pa.list_(pa.float32())))
                if "query_id" in batch.schema.names:
                    batch = batch.append_column("least", pa.array(first_thresholds(v, batch.column("query_id").to_numpy(), known, known_ids, k)))
                yield batch

    asked = tables.write(asked.mapInArrow(measured, "query_id long, v array<long>, d array<float>, least long"), "asked")
    rows = rows.mapInArrow(measured, "vec_id long, v array<long>, d array<float>")
    n_rows, n_queries = max(1, -(-dims // row_block)), max(1, -(-asked.count() // query_block))
    place = F.monotonically_increasing_id()
    left = rows.withColumn("rb", F.pmod(place, F.lit(n_rows)).cast("int")).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(n_queries - 1))))
    right = asked.withColumn("qb", F.pmod(place, F.lit(n_queries)).cast("int")).withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(n_rows - 1))))
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])

    def run(x: pa.Table, q: pa.Table) -> pa.Table:
        if not len(x) or not len(q):
            return schema.empty_table()
        found, _ = search_block(
            matrix(q.column("v"), np.int64), q.column("query_id").to_numpy(), matrix(q.column("d"), np.float32), q.column("least").to_numpy(),
            matrix(x.column("v"), np.int64), x.column("vec_id").to_numpy(), matrix(x.column("d"), np.float32), sizes, k,
        )
        return pa.table(found, schema=schema)

    found = left.groupBy("rb", "qb").cogroup(right.groupBy("rb", "qb")).applyInArrow(run, "query_id long, vec_id long, score long")
    return best(found, k, descending=True)


def search_table(embeddings: DataFrame, every: int = 20, k: int = 20, scale: int = 64, **options) -> DataFrame:
    """Queries: rows whose id is divisible by ``every``, against all rows."""
    rows = embeddings.where(usable(F.col("embedding"))).select("vec_id", quantised(F.col("embedding"), scale).alias("v"))
    return search(rows, rows.where(F.col("vec_id") % every == 0), k, **options)
