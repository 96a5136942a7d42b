"""Costs of many centroid sets over points that are read once: blocks of points, each with a tree of medians.

A node whose box lies nearest to one centroid of a set gives its share from its sums; only nodes that a border
cuts are opened, down to their points.  The costs are those of a whole scan, up to the order of sums.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import RDD
from pyspark.sql import DataFrame

#: Points of a block and of a leaf; pairs of node and set that are judged at once.
BLOCK, LEAF, PAIRS = 1 << 18, 24, 1 << 13


class Tree:
    """points (d, leaves, places) and their weights (0: no point); nodes are numbered as in a heap, with their weight, sums, middles and half widths."""

    def __init__(self, points: np.ndarray, weights: np.ndarray, stats: np.ndarray):
        self.points, self.weights, self.stats, self.d = points, weights, stats, len(points)
        self.first = len(stats) - weights.shape[0]  # the first leaf's node

    @staticmethod
    def build(x: np.ndarray, w: np.ndarray) -> Tree:
        n, d = x.shape
        depth = max(0, int(np.ceil(np.log2(max(1, n) / LEAF))))
        leaves, parts = 1 << depth, [np.arange(n)]
        for _ in range(depth):
            halves = []
            for rows in parts:
                if len(rows) < 2:
                    halves += [rows, rows[:0]]
                    continue
                mine, at = x[rows], len(rows) // 2
                order = np.argpartition(mine[:, np.ptp(mine, axis=0).argmax()], at)
                halves += [rows[order[:at]], rows[order[at:]]]
            parts = halves
        places = max(1, max(map(len, parts)))
        points, weights = np.zeros((d, leaves, places)), np.zeros((leaves, places))
        stats = np.zeros((2 * leaves - 1, 2 + 3 * d))  # weight, squares, sums, lowest, highest
        stats[:, 2 + d : 2 + 2 * d], stats[:, 2 + 2 * d :] = np.inf, -np.inf
        for i, rows in enumerate(parts):
            mine, v, node = x[rows], w[rows], leaves - 1 + i
            points[:, i, : len(rows)], weights[i, : len(rows)] = mine.T, v
            stats[node, 0], stats[node, 1], stats[node, 2 : 2 + d] = v.sum(), (v[:, None] * mine * mine).sum(), v @ mine
            if len(rows):
                stats[node, 2 + d : 2 + 2 * d], stats[node, 2 + 2 * d :] = mine.min(0), mine.max(0)
        for level in range(depth - 1, -1, -1):
            at = np.arange((1 << level) - 1, (2 << level) - 1)
            a, b = stats[2 * at + 1], stats[2 * at + 2]
            stats[at] = a + b
            stats[at, 2 + d : 2 + 2 * d] = np.minimum(a[:, 2 + d : 2 + 2 * d], b[:, 2 + d : 2 + 2 * d])
            stats[at, 2 + 2 * d :] = np.maximum(a[:, 2 + 2 * d :], b[:, 2 + 2 * d :])
        low, high = stats[:, 2 + d : 2 + 2 * d].copy(), stats[:, 2 + 2 * d :].copy()
        empty = low > high
        low[empty] = high[empty] = 0
        stats[:, 2 + d : 2 + 2 * d], stats[:, 2 + 2 * d :] = (low + high) / 2, (high - low) / 2
        return Tree(points, weights, stats)

    def pack(self) -> tuple[bytes, bytes, bytes, int, int]:
        return self.points.tobytes(), self.weights.tobytes(), self.stats.tobytes(), self.d, self.weights.shape[1]

    @staticmethod
    def unpack(points: bytes, weights: bytes, stats: bytes, d: int, places: int) -> Tree:
        w = np.frombuffer(weights).reshape(-1, places)
        return Tree(np.frombuffer(points).reshape(d, -1, places), w, np.frombuffer(stats).reshape(-1, 2 + 3 * d))

    def costs(self, sets: np.ndarray) -> np.ndarray:
        """Sum of weighted squared distances to the nearest centroid, for each of the sets (sets, k, d)."""
        total, squares, waiting = np.zeros(len(sets)), (sets * sets).sum(2), [(np.zeros(len(sets), np.int64), np.arange(len(sets)))]
        while waiting:
            nodes, which = waiting.pop()
            if len(nodes) > PAIRS:
                waiting += [(nodes[i : i + PAIRS], which[i : i + PAIRS]) for i in range(0, len(nodes), PAIRS)]
                continue
            s, c, d = self.stats[nodes], sets[which], self.d
            far = squares[which] - 2 * (c * s[:, None, 2 + d : 2 + 2 * d]).sum(2)
            best = far.argmin(1)
            near, at = c[np.arange(len(c)), best], np.arange(len(c))
            sure = (far - far[at, best][:, None] >= 2 * (np.abs(c - near[:, None]) * s[:, None, 2 + 2 * d :]).sum(2)).all(1)
            share = s[:, 0] * squares[which, best] - 2 * (s[:, 2 : 2 + d] * near).sum(1) + s[:, 1]
            total += np.bincount(which[sure], share[sure], len(sets))
            leaf = ~sure & (nodes >= self.first)
            if leaf.any():
                total += np.bincount(which[leaf], s[leaf, 1] + self._open(nodes[leaf] - self.first, c[leaf], squares[which[leaf]]), len(sets))
            cut = ~sure & (nodes < self.first)
            if cut.any():
                waiting.append((np.concatenate([2 * nodes[cut] + 1, 2 * nodes[cut] + 2]), np.tile(which[cut], 2)))
        return total

    def _open(self, leaves: np.ndarray, c: np.ndarray, squares: np.ndarray) -> np.ndarray:
        points, least = [self.points[i][leaves] for i in range(self.d)], None
        for j in range(c.shape[1]):
            dist = -2 * c[:, j, :1] * points[0]
            for i in range(1, self.d):
                dist -= 2 * c[:, j, i, None] * points[i]
            dist += squares[:, j, None]
            least = dist if least is None else np.minimum(least, dist, out=least)
        return (least * self.weights[leaves]).sum(1)


def summed(parts: RDD) -> np.ndarray:
    """The sum of one array a partition: few meet on the driver, many in tasks first."""
    return sum(parts.collect()) if parts.getNumPartitions() <= 64 else parts.treeReduce(np.add)


_PACKED = ["points", "weights", "stats", "d", "places"]


def point_trees(df: DataFrame, cols: list[str], weight: str | None = None) -> RDD:
    """The points as packed trees, one for each block of a partition."""

    def run(batches):
        held, rows = [], 0

        def packed():
            full = np.concatenate(held)
            tree = Tree.build(full[:, :-1], full[:, -1]).pack()
            return pa.RecordBatch.from_arrays([*(pa.array([v], pa.binary()) for v in tree[:3]), *(pa.array([v], pa.int32()) for v in tree[3:])], names=_PACKED)

        for batch in batches:
            if not batch.num_rows:
                continue
            w = batch.column(weight).to_numpy(zero_copy_only=False) if weight else np.ones(batch.num_rows)
            held.append(np.column_stack([*(batch.column(n).to_numpy(zero_copy_only=False) for n in cols), w]).astype(float))
            rows += batch.num_rows
            if rows >= BLOCK:
                yield packed()
                held, rows = [], 0
        if held:
            yield packed()

    points, tasks = df.select(*cols, *([weight] if weight else [])), df.sparkSession.sparkContext.defaultParallelism
    few = points.rdd.getNumPartitions() < tasks
    points = points.repartition(tasks) if few else points.coalesce(2 * tasks)  # read once, judged in every round
    return points.mapInArrow(run, "points binary, weights binary, stats binary, d int, places int").rdd.map(tuple)


def tree_costs(trees: RDD, sets: np.ndarray) -> np.ndarray:
    """Costs of centroid sets (sets, k, d): one job, without a plan to make and, on up to 64 partitions, without a shuffle."""
    sets = np.asarray(sets, float)

    def run(rows):
        total = np.zeros(len(sets))
        for row in rows:
            total += Tree.unpack(*row).costs(sets)
        yield total

    return summed(trees.mapPartitions(run))
