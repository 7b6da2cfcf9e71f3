"""Vectors as arrays: native higher-order functions, and Arrow kernels for long ones."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def axpy(alpha: float, x: Column, y: Column) -> Column:
    """alpha * x + y."""
    return F.zip_with(x, y, lambda p, q: p * F.lit(float(alpha)) + q)


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


@F.pandas_udf(T.DoubleType())
def dot_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    """The dot product over Arrow batches, for vectors too long for code generation."""
    return pd.Series([float(np.dot(x, y)) if x is not None and y is not None else None for x, y in zip(a, b)])


def sum_vectors(df: DataFrame, keys: list[str], vector: str, weight: str | None = None) -> DataFrame:
    """(keys, coord, value, weight): the weighted sum of vectors in coordinate form, partially aggregated before the exchange."""
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    long = df.select(*keys, w.alias("weight"), F.posexplode(vector).alias("coord", "x"))
    return long.groupBy(*keys, "coord").agg(F.sum(F.col("x") * F.col("weight")).alias("value"), F.sum("weight").alias("weight"))


def mean_vectors(df: DataFrame, keys: list[str], vector: str, weight: str | None = None) -> DataFrame:
    """(keys, coord, value): the weighted mean; rows of weight 0 do not count."""
    return sum_vectors(df, keys, vector, weight).where("weight > 0").select(*keys, "coord", (F.col("value") / F.col("weight")).alias("value"))
