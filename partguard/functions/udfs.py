"""Arrow and plain functions for where built-in expressions don't do: distances, pooled percentiles, row makers."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def ks_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.max(np.abs(np.asarray(x) - np.asarray(y)))) if x is not None and y is not None else None for x, y in zip(a, b)])


@F.pandas_udf(T.DoubleType())
def w1_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.sum(np.abs(np.asarray(x) - np.asarray(y)))) if x is not None and y is not None else None for x, y in zip(a, b)])


@F.pandas_udf(T.DoubleType())
def dts_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x, y):
        if x is None or y is None:
            return None
        x, y = np.asarray(x, float), np.asarray(y, float)
        both = np.concatenate([x, y])
        span = np.ptp(both)
        if not span:
            return 0.0
        d = np.var((both - both.min()) / span)
        return float(np.sum(np.abs(x - y)) / span / (d * (1 - d)))

    return pd.Series([one(x, y) for x, y in zip(a, b)])


@F.pandas_udf(T.DoubleType())
def weighted_median(value: pd.Series, weight: pd.Series) -> float:
    """Smallest value with at least half of the weight at or below it."""
    order = np.argsort(value.to_numpy(), kind="stable")
    total = np.cumsum(weight.to_numpy()[order])
    return float(value.to_numpy()[order][np.searchsorted(total, total[-1] / 2)])


@F.udtf(returnType=T.StructType([T.StructField("rank", T.IntegerType()), T.StructField("value", T.DoubleType())]))
class PercentileRows:
    """The entries of a percentile vector as rows."""

    def eval(self, vector):
        for i, x in enumerate(vector or [], 1):
            yield i, x


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udf.register("ks_distance", ks_distance)
    spark.udf.register("w1_distance", w1_distance)
    spark.udf.register("dts_distance", dts_distance)
    spark.udtf.register("percentile_rows", PercentileRows)
