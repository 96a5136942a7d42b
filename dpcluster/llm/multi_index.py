"""Approximate nearest neighbours with an inverted multi-index.

The halves of the vectors are quantised on their own; a cell is a pair of centroids.  A query walks
the pairs in the order of their summed distance with a heap, until the cells hold enough rows, and
all rows of these cells are ranked by their exact distance.

The codebooks are fitted on a bounded sample, every row is indexed.  How many rows a query visits
is measured: for a bounded sample of queries the true neighbours are found by a full scan, and the
walk goes so far that ``recall`` of them are met.  Cells are dealt to shards of bounded size; a cell
that is larger is split over several shards, so copies of one vector do not gather in a task.

Defined results: null, zero, empty or non-finite vectors take no part, nor do rows without an id or
with another length than the most common one; a query's candidates are rows with other ids; a
repeated query id is searched once, with its least vector; repeated rows are candidates each.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpcluster.llm import scratch
from dpcluster.llm.scratch import Scratch
from dpcluster.llm.vectors import best, matrix, top, usable

SAMPLE, PROBES, RECALL, SHARD_ROWS, QUERY_BLOCK = 20_000, 96, 0.97, 16_384, 2_048


def codebook(x: np.ndarray, k: int, rounds: int = 8, seed: int = 3) -> np.ndarray:
    """k-means centroids of a sample."""
    x = np.unique(x, axis=0)
    k = min(k, len(x))
    c = x[np.random.default_rng(seed).choice(len(x), k, replace=False)].astype(np.float64)
    for _ in range(rounds):
        near = nearest(x, c)
        n = np.bincount(near, minlength=k)
        sums = np.zeros_like(c)
        np.add.at(sums, near, x)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
    return c


def squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return (x * x).sum(1)[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.concatenate([squared(x[i : i + 8192], c).argmin(1) for i in range(0, len(x), 8192)]) if len(x) else np.zeros(0, np.int64)


def walk(d1: np.ndarray, d2: np.ndarray, counts: np.ndarray, rows: int) -> list[int]:
    """Cells in the order of summed distance until they hold so many rows; empty ones are left out."""
    o1, o2, k2 = d1.argsort(kind="stable").tolist(), d2.argsort(kind="stable").tolist(), len(d2)
    a, b = d1[o1].tolist(), d2[o2].tolist()
    heap, ahead, out, held = [(a[0] + b[0], 0, 0)], [0] * len(a), [], 0
    while heap and held < rows:
        _, i, j = heapq.heappop(heap)
        cell = o1[i] * k2 + o2[j]
        if counts[cell]:
            out.append(cell)
            held += int(counts[cell])
        ahead[i] = j + 1
        # a pair is reached once its left and upper neighbours have been taken
        if j + 1 < k2 and (i == 0 or ahead[i - 1] > j + 1):
            heapq.heappush(heap, (a[i] + b[j + 1], i, j + 1))
        if i + 1 < len(a) and ahead[i + 1] == j:
            heapq.heappush(heap, (a[i + 1] + b[j], i + 1, j))
    return out


class Index:
    """Codebooks, rows of each cell, and the shards of the cells; all of bounded size."""

    def __init__(self, first: np.ndarray, second: np.ndarray, shard_rows: int = SHARD_ROWS):
        self.first, self.second, self.shard_rows = first, second, shard_rows
        self.counts = np.zeros(len(first) * len(second), np.int64)

    def cells(self, x: np.ndarray) -> np.ndarray:
        h = self.first.shape[1]
        return nearest(x[:, :h], self.first) * len(self.second) + nearest(x[:, h:], self.second)

    def deal(self) -> None:
        """Cells side by side share a shard; larger cells have several of their own."""
        self.splits = np.maximum(1, -(-self.counts // self.shard_rows))
        self.start, at, room = np.zeros(len(self.counts), np.int64), 0, self.shard_rows
        for cell in np.flatnonzero(self.counts):
            n, parts = int(self.counts[cell]), int(self.splits[cell])
            if n > room:
                at, room = at + (room < self.shard_rows), self.shard_rows
            self.start[cell] = at
            if parts > 1:
                at, room = at + parts, self.shard_rows
            else:
                room -= n
        self.shards = at + 1

    def visits(self, q: np.ndarray, rows: int) -> list[list[int]]:
        h = self.first.shape[1]
        d1, d2 = squared(q[:, :h], self.first), squared(q[:, h:], self.second)
        return [walk(d1[i], d2[i], self.counts, rows) for i in range(len(q))]


def exact_scan(rows: DataFrame, q: np.ndarray, q_ids: np.ndarray, k: int) -> DataFrame:
    """True neighbours of a few queries by a full scan; each batch sends on k rows a query."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x, ids = matrix(batch.column("v")), batch.column("vec_id").to_numpy()
                got = []
                for i in range(len(q)):
                    other = np.flatnonzero(ids != q_ids[i])
                    d = np.sqrt(((x[other] - q[i]) ** 2).sum(1))
                    got += [(int(q_ids[i]), int(ids[other[j]]), float(d[j]), int(batch.column("cell")[int(other[j])].as_py())) for j in top(d, ids[other], k)]
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*got), (pa.int64(), pa.int64(), pa.float64(), pa.int64()))], names=["query_id", "vec_id", "score", "cell"])

    found = rows.mapInArrow(run, "query_id long, vec_id long, score double, cell long")
    from pyspark.sql import Window

    w = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def search(rows: DataFrame, queries: DataFrame, k: int = 10, recall: float = RECALL, shard_rows: int = SHARD_ROWS, query_block: int = QUERY_BLOCK, centroids: int | None = None) -> DataFrame:
    """rows and queries: vec_id long, v array<double>. Returns query_id, rank, vec_id, score (distance)."""
    spark, tables = rows.sparkSession, Scratch(rows.sparkSession, "multi-index")
    scratch.share_code(spark)
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), "v").where("vec_id is not null")
    length = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    out = "query_id long, rank int, vec_id long, score double"
    if length is None:
        return spark.createDataFrame([], out)
    total, rows = length["count"], rows.where(F.size("v") == length["n"])
    sample = matrix(rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("v").toArrow().column("v"))
    half, size = length["n"] // 2, centroids or int(np.clip(round((total / 64) ** 0.5), 2, 256))
    index = Index(codebook(sample[:, :half], size), codebook(sample[:, half:], size), shard_rows)

    def assign(batches):
        for batch in batches:
            cells = index.cells(matrix(batch.column("v"))) if batch.num_rows else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(cells, pa.int64()), batch.column("v")], names=["vec_id", "cell", "v"])

    held = tables.write(rows.mapInArrow(assign, "vec_id long, cell long, v array<double>"), "cells")
    for r in held.groupBy("cell").count().collect():  # at most centroids ** 2 rows
        index.counts[r["cell"]] = r["count"]
    index.deal()
    asked = queries.select(F.col("vec_id").cast("long").alias("query_id"), "v").where(F.col("query_id").isNotNull() & (F.size("v") == length["n"])).groupBy("query_id").agg(F.min("v").alias("v"))
    asked = tables.write(asked, "asked")

    probes = asked.orderBy(F.xxhash64("query_id"), "query_id").limit(PROBES).toArrow()
    need = total
    if len(probes):
        p, p_ids = matrix(probes.column("v")), probes.column("query_id").to_numpy()
        truth = exact_scan(held, p, p_ids, k).collect()  # at most PROBES * k rows
        paths = {int(i): path for i, path in zip(p_ids, index.visits(p, total + 1))}
        seen = {i: dict(zip(path, np.cumsum(index.counts[path]) - index.counts[path] + 1)) for i, path in paths.items()}
        depths = sorted(int(seen[r["query_id"]][r["cell"]]) for r in truth)
        need = depths[min(len(depths) - 1, int(np.ceil(recall * len(depths))))] if depths else total
    need = max(need, 8 * k)

    blocks = max(1, -(-asked.count() // query_block))
    shared = spark.sparkContext.broadcast(index)  # codebooks and cells: bounded by centroids ** 2

    def visit(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            ix, got = shared.value, []
            for i, path in enumerate(ix.visits(matrix(batch.column("v")), need)):
                by: dict[int, list[int]] = {}
                for c in path:
                    for s in range(int(ix.splits[c])):
                        by.setdefault(int(ix.start[c]) + s, []).append(c)
                got += [(i, s, np.asarray(c, "<i4").tobytes()) for s, c in by.items()]
            at = pa.array([g[0] for g in got], pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column("query_id").take(at), pa.array([g[1] for g in got], pa.int32()), pa.array([g[2] for g in got], pa.binary()), batch.column("qb").take(at), batch.column("v").take(at)], names=["query_id", "shard", "cells", "qb", "v"])

    place = F.monotonically_increasing_id()
    visits = asked.withColumn("qb", F.pmod(place, F.lit(blocks)).cast("int")).mapInArrow(visit, "query_id long, shard int, cells binary, qb int, v array<double>")

    def deal(batches):
        for batch in batches:
            ix, cell = shared.value, batch.column("cell").to_numpy()
            shard = ix.start[cell] + batch.column("salt").to_numpy() % ix.splits[cell]
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("cell"), pa.array(shard.astype(np.int32)), batch.column("v")], names=["vec_id", "cell", "shard", "v"])

    dealt = held.withColumn("salt", place).mapInArrow(deal, "vec_id long, cell long, shard int, v array<double>").withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def rank(x: pa.Table, q: pa.Table) -> pa.Table:
        if not len(x) or not len(q):
            return schema.empty_table()
        xs, ids, cells, qs, q_ids = matrix(x.column("v")), x.column("vec_id").to_numpy(), x.column("cell").to_numpy(), matrix(q.column("v")), q.column("query_id").to_numpy()
        names, at = np.unique(cells, return_inverse=True)
        got = []
        for i, wanted in enumerate(q.column("cells").to_pylist()):
            mine = np.isin(names, np.frombuffer(wanted, "<i4"), assume_unique=True)[at] & (ids != q_ids[i])
            rows = np.flatnonzero(mine)
            near = squared(qs[i : i + 1], xs)[0][rows] if 4 * len(rows) > len(xs) else squared(qs[i : i + 1], xs[rows])[0]
            if len(rows) > k:  # ties and rounding: whatever may be among the k nearest is measured exactly
                rows = rows[near <= np.partition(near, k - 1)[k - 1] + 1e-6 * (1 + np.abs(near).max())]
            d = np.sqrt(((xs[rows] - qs[i]) ** 2).sum(1))
            pick = top(d, ids[rows], k)
            got.append((np.full(len(pick), q_ids[i]), ids[rows[pick]], d[pick]))
        return pa.table([np.concatenate(c) for c in zip(*got)], schema=schema)

    found = dealt.groupBy("shard", "qb").cogroup(visits.groupBy("shard", "qb")).applyInArrow(rank, "query_id long, vec_id long, score double")
    return best(found, k, descending=False)


def search_table(embeddings: DataFrame, every: int = 100, k: int = 10, **options) -> DataFrame:
    """Queries: rows whose id is divisible by ``every``, against all rows."""
    rows = embeddings.where(usable(F.col("embedding"), nonzero=True)).select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    return search(rows, rows.where(F.col("vec_id") % every == 0), k, **options)
