"""One entry to all methods, in the manner of an estimator and its model."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from dpcluster.operators import block_average, evolve, grid_kmeans, noisy_lloyd, two_stage
from dpcluster.operators.lloyd import Clustering, assign


@dataclass
class PrivateKMeansModel:
    """transform labels rows; labels of private rows are no private output, centroids are."""

    result: Clustering
    cols: list[str]

    @property
    def centroids(self):
        return self.result.centroids

    def transform(self, df: DataFrame) -> DataFrame:
        return assign(df, self.cols, self.result.centroids)


@dataclass
class PrivateKMeans:
    """method: two_stage, grid_kmeans, noisy_lloyd, block_average or evolve; n: the public number of rows."""

    method: str = "two_stage"
    k: int = 2
    epsilon: float = 1.0
    n: int | None = None
    options: dict = field(default_factory=dict)

    def fit(self, df: DataFrame, cols: list[str]) -> PrivateKMeansModel:
        n = self.n if self.n is not None else df.count()
        run = {
            "two_stage": lambda: two_stage.two_stage(df, cols, self.k, self.epsilon, n, **self.options),
            "grid_kmeans": lambda: grid_kmeans.grid_kmeans(df, cols, self.k, self.epsilon, n, **self.options),
            "noisy_lloyd": lambda: noisy_lloyd.noisy_lloyd(df, cols, self.k, self.epsilon, **self.options),
            "block_average": lambda: block_average.block_average(df, cols, self.k, self.epsilon, n, **self.options),
            "evolve": lambda: evolve.evolve(df, cols, self.k, self.epsilon, n, **self.options),
        }
        return PrivateKMeansModel(run[self.method](), cols)
