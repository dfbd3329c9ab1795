"""Models and kernels as SQL functions: scalar, aggregate and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from landmark_kkm.functions.kernels import Kernel
from landmark_kkm.functions.payloads import Dense
from landmark_kkm.operators.cluster import ClusterModel, costs
from landmark_kkm.operators.coefficients import CoefficientBlock
from landmark_kkm.session import ship


def register(spark: SparkSession, blocks: list[CoefficientBlock] | None = None, kernel: Kernel | None = None, model: ClusterModel | None = None) -> list[str]:
    """kernel_vector(x) and embed(x) of dense vectors, nearest(y), vector_sum(y), vector_mean(y), and the table functions explode_kernel(id, x) and
    cluster_partials(TABLE(id, y)). Those that need blocks or a model are registered only if these are given; the names come back."""
    ship(spark)
    names = []
    vector = T.ArrayType(T.DoubleType())

    def rows(x: pd.Series) -> Dense:
        return Dense(np.array(x.tolist(), dtype=float).reshape(len(x), -1))

    if blocks is not None and kernel is not None:
        held = spark.sparkContext.broadcast((blocks, kernel))

        @pandas_udf(vector)
        def kernel_vector(x: pd.Series) -> pd.Series:
            parts, kind = held.value
            return pd.Series(list(np.hstack([kind.matrix(rows(x), b.landmarks.rows) for b in parts])))

        @pandas_udf(vector)
        def embed(x: pd.Series) -> pd.Series:
            parts, kind = held.value
            return pd.Series(list(np.hstack([b.apply(rows(x), kind) for b in parts])))

        @udtf(returnType="landmark long, value double")
        class ExplodeKernel:
            """One row for each landmark: its id and the kernel of x with it."""

            def eval(self, x):
                parts, kind = held.value
                one = Dense(np.array([x], dtype=float))
                for b in parts:
                    for i, v in zip(b.landmarks.ids, kind.matrix(one, b.landmarks.rows)[0]):
                        yield int(i), float(v)

        spark.udf.register("kernel_vector", kernel_vector)
        spark.udf.register("embed", embed)
        spark.udtf.register("explode_kernel", ExplodeKernel)
        names += ["kernel_vector", "embed", "explode_kernel"]

    if model is not None:
        about = spark.sparkContext.broadcast((model.centroids, model.discrepancy, model.extra))

        @pandas_udf("int")
        def nearest(y: pd.Series) -> pd.Series:
            centroids, discrepancy, extra = about.value
            return pd.Series(costs(rows(y).rows, centroids, discrepancy, extra).argmin(1).astype(np.int32))

        @udtf(returnType="cluster int, z array<double>, g long")
        class ClusterPartials:
            """Sums and counts of a table's vectors by nearest centroid, one row for each cluster that the partition has."""

            def __init__(self):
                self.sums = {}

            def eval(self, y):
                centroids, discrepancy, extra = about.value
                v = np.array(y["y"] if hasattr(y, "asDict") else y, dtype=float)
                c = int(costs(v[None], centroids, discrepancy, extra).argmin())
                z, g = self.sums.get(c, (0.0, 0))
                self.sums[c] = (z + v, g + 1)

            def terminate(self):
                for c, (z, g) in sorted(self.sums.items()):
                    yield c, z.tolist(), g

        spark.udf.register("nearest", nearest)
        spark.udtf.register("cluster_partials", ClusterPartials)
        names += ["nearest", "cluster_partials"]

    @pandas_udf(vector)
    def vector_sum(y: pd.Series) -> list[float]:
        return np.sum(rows(y).rows, axis=0).tolist()

    @pandas_udf(vector)
    def vector_mean(y: pd.Series) -> list[float]:
        return np.mean(rows(y).rows, axis=0).tolist()

    spark.udf.register("vector_sum", vector_sum)
    spark.udf.register("vector_mean", vector_mean)
    return [*names, "vector_sum", "vector_mean"]


#: The vector sum without Python, for plans that stay in the JVM.
def native_vector_sum(column: str, size: int):
    return F.array(*[F.sum(F.get(F.col(column), i)) for i in range(size)])
