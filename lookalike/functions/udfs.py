"""The SQL surface: scalar functions, an aggregate, table functions."""

from __future__ import annotations

import heapq
import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .caps import boundary_weight


def _flat(a: pa.Array) -> np.ndarray:
    return a.flatten().to_numpy(zero_copy_only=False).reshape(len(a), -1)


def register(spark: SparkSession) -> None:
    """Registers ``twin_sim(a, b)``, ``twin_weight(cos, theta, d)``, ``vec_avg(v)``,
    ``explode_vector(v)`` and ``top_twins(table, k)`` for SQL.

    Inside DataFrame code the Column forms in ``functions.vectors`` are better: they stay in the JVM.
    """

    @F.arrow_udf("double")
    def twin_sim(a: pa.Array, b: pa.Array) -> pa.Array:
        x, y = _flat(a), _flat(b)
        n = np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1)
        return pa.array(np.divide((x * y).sum(1), n, out=np.zeros(len(x)), where=n > 0))

    @F.pandas_udf("double")
    def twin_weight(cos: pd.Series, theta: pd.Series, d: pd.Series) -> pd.Series:
        out = np.empty(len(cos))
        for (t, n), at in cos.groupby([theta, d]).groups.items():
            rows = cos.index.get_indexer(at)
            out[rows] = boundary_weight(cos.to_numpy()[rows], float(t), int(n))
        return pd.Series(out)

    @F.pandas_udf("array<double>")
    def vec_avg(v: pd.Series) -> list[float]:
        return np.mean(np.stack(v.to_numpy()), axis=0).tolist()

    @F.udtf(returnType="dim int, value double")
    class ExplodeVector:
        def eval(self, v):
            for i, x in enumerate(v or ()):
                yield i, float(x)

    @F.udtf(returnType="v long, u long, rank int, sim double")
    class TopTwins:
        """``top_twins(TABLE(scored) PARTITION BY (v), k)`` over rows of v, u, sim: a heap of k rows per partition."""

        def __init__(self):
            self.heap = []

        def eval(self, row, k):
            item = (row["sim"], -row["u"], row["v"])
            if len(self.heap) < k:
                heapq.heappush(self.heap, item)
            else:
                heapq.heappushpop(self.heap, item)

        def terminate(self):
            for rank, (sim, u, v) in enumerate(sorted(self.heap, reverse=True), 1):
                yield v, -u, rank, sim

    spark.udtf.register("top_twins", TopTwins)
    spark.udf.register("twin_sim", twin_sim)
    spark.udf.register("twin_weight", twin_weight)
    spark.udf.register("vec_avg", vec_avg)
    spark.udtf.register("explode_vector", ExplodeVector)


THETA = math.pi / 3
