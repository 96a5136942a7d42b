"""Functions and table functions for SQL."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def nearest_udf(centroids: list[list[float]]):
    """The number of the nearest centroid from one column for each coordinate, in Arrow batches."""
    import numpy as np
    import pandas as pd

    c = np.asarray(centroids, float)

    def nearest(*columns: pd.Series) -> pd.Series:
        x = np.column_stack(columns)
        return pd.Series(((x[:, None, :] - c[None]) ** 2).sum(2).argmin(1).astype("int32"))

    nearest.__annotations__ = {"columns": pd.Series, "return": pd.Series}
    return F.pandas_udf(nearest, "int")


def weighted_centroid(cols: list[str], weight: str) -> Column:
    """An aggregate: the weighted mean of points, as an array; partial sums are combined before any shuffle."""
    return F.array(*(F.sum(F.col(weight) * F.col(c)) / F.sum(weight) for c in cols))


def register(spark: SparkSession) -> None:
    """grid_cell, laplace_of_uniform, nearest2 as SQL functions that the optimizer inlines, and the table function grid_cells."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION grid_cell(x DOUBLE, m INT) RETURNS BIGINT RETURN greatest(0L, least(cast(floor((x + 1) / 2 * m) AS BIGINT), cast(m - 1 AS BIGINT)))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION laplace_of_uniform(u DOUBLE, scale DOUBLE) RETURNS DOUBLE RETURN -scale * sign(u - 0.5) * ln(1 - 2 * abs(u - 0.5))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION nearest2(x ARRAY<DOUBLE>, c ARRAY<ARRAY<DOUBLE>>) RETURNS INT RETURN array_position(transform(c, p -> aggregate(zip_with(x, p, (a, b) -> (a - b) * (a - b)), 0D, (s, v) -> s + v)), array_min(transform(c, p -> aggregate(zip_with(x, p, (a, b) -> (a - b) * (a - b)), 0D, (s, v) -> s + v)))) - 1")

    class GridCells:
        def eval(self, m: int, d: int):
            for cell in range(m**d):
                index, rest = [], cell
                for _ in range(d):
                    index.append(rest % m)
                    rest //= m
                yield cell, [2 * (i + 0.5) / m - 1 for i in reversed(index)]

    spark.udtf.register("grid_cells", F.udtf(GridCells, returnType="cell: long, centre: array<double>"))
