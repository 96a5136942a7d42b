"""What the vector searches share: which rows take part, and packed columns."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(vector: Column, nonzero: bool = False) -> Column:
    """Not null, not empty, and every component there and finite."""
    v = vector.cast("array<double>")
    fine = vector.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    if nonzero:
        fine = fine & F.exists(v, lambda x: x != 0)
    return F.coalesce(fine, F.lit(False))


def matrix(column: pa.ChunkedArray | pa.Array, dtype=np.float64) -> np.ndarray:
    """Lists of one length as rows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).astype(dtype, copy=False).reshape(n, -1) if n else np.zeros((0, 0), dtype)


def best(df: DataFrame, k: int, descending: bool) -> DataFrame:
    """The k best rows of each query, ranked from 1; ties go to smaller ids.

    Spark limits each task to k rows a query before it shuffles."""
    from pyspark.sql import Window

    order = F.col("score").desc() if descending else F.col("score").asc()
    ranked = df.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(order, F.col("vec_id").asc())))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k smallest scores, ties by id."""
    if len(scores) > k:
        cut = np.partition(scores, k - 1)[k - 1]
        keep = np.flatnonzero(scores <= cut)
    else:
        keep = np.arange(len(scores))
    return keep[np.lexsort((ids[keep], scores[keep]))[:k]]
