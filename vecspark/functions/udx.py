"""Registered user functions: scalar, aggregate and table functions over vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def vec_l2(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.stack(a.to_numpy()).astype(np.float64), np.stack(b.to_numpy()).astype(np.float64)
    return pd.Series(((x - y) ** 2).sum(1))


@F.pandas_udf(T.DoubleType())
def vec_dot(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.stack(a.to_numpy()).astype(np.float64), np.stack(b.to_numpy()).astype(np.float64)
    return pd.Series((x * y).sum(1))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_mean(a: pd.Series) -> list:
    """Mean of a group's vectors."""
    return np.stack(a.to_numpy()).astype(np.float64).mean(0).tolist()


@F.udtf(returnType=T.StructType([T.StructField("cid", T.IntegerType()), T.StructField("dist", T.DoubleType())]))
class NearestLists:
    """(cid, dist) of the n centroids nearest to a vector."""

    def eval(self, vec: list, centroids: list, n: int):
        x = np.asarray(vec, np.float64)
        d = np.round(((np.asarray(centroids, np.float64) - x) ** 2).sum(1), 9)
        for c in np.argsort(d, kind="stable")[:n]:
            yield int(c), float(d[c])


@F.udtf(returnType=T.StructType([T.StructField("blk", T.IntegerType()), T.StructField("vals", T.ArrayType(T.FloatType()))]))
class DimensionBlocks:
    """The dimensions behind the head in blocks; the last may be shorter."""

    def eval(self, vec: list, d1: int, step: int):
        for i, at in enumerate(range(d1, len(vec), step)):
            yield i, [float(v) for v in vec[at : at + step]]


def register(spark: SparkSession) -> None:
    """vec_l2, vec_dot, vec_mean, nearest_lists and dimension_blocks for SQL."""
    spark.udf.register("vec_l2", vec_l2)
    spark.udf.register("vec_dot", vec_dot)
    spark.udf.register("vec_mean", vec_mean)
    spark.udtf.register("nearest_lists", NearestLists)
    spark.udtf.register("dimension_blocks", DimensionBlocks)
