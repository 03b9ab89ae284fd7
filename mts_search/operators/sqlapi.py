"""SQL surface: window enumeration and kNN as table functions, views of the series families."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..functions import kernels as K
from . import fixtures as X


@udtf(returnType="start int, vals array<double>")
class WindowsOf:
    """windows_of(values, q): every window of an array."""

    def eval(self, values: list, q: int):
        for i in range(len(values) - q + 1):
            yield i, [float(x) for x in values[i : i + q]]


@udtf(returnType="start int, distance double")
class KnnSubsequences:
    """knn_subsequences(values, query, k): the k windows of an array nearest to a query array."""

    def eval(self, values: list, query: list, k: int):
        d = K.profile(np.array([values], float), np.array([query], float))
        for i in np.lexsort((np.arange(len(d)), d))[:k]:
            yield int(i), float(np.sqrt(d[i]))


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Registers the functions and, given the tables, a view per series family."""
    spark.udtf.register("windows_of", WindowsOf)
    spark.udtf.register("knn_subsequences", KnnSubsequences)
    for name, fx in X.FIXTURES.items() if sf_dir else ():
        fx.points(spark, sf_dir).createOrReplaceTempView(name)
