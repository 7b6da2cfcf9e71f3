"""Vector functions as Arrow UDFs and a grouped aggregate, for vectors too long for column expressions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def _rows(v: pa.Array) -> np.ndarray:
    return v.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(v), -1)


def vec_dot(a: Column, b: Column) -> Column:
    """The inner product of two arrays of one length per batch."""

    @F.arrow_udf("double")
    def dot(x: pa.Array, y: pa.Array) -> pa.Array:
        return pa.array((_rows(x) * _rows(y)).sum(1)) if len(x) else pa.array([], pa.float64())

    return dot(a, b)


def vec_axpy(alpha: float, a: Column, b: Column) -> Column:
    """alpha a + b."""

    @F.arrow_udf("array<double>")
    def axpy(x: pa.Array, y: pa.Array) -> pa.Array:
        return pa.array(list(alpha * _rows(x) + _rows(y)), pa.list_(pa.float64()))

    return axpy(a, b)


def vec_avg(a: Column) -> Column:
    """The mean vector of a group. All rows of a group meet in one task: for groups of bounded size; `functions.vectors.sum_vectors` has partial sums."""

    @F.arrow_udf("array<double>")
    def avg(x: pa.Array) -> list[float]:
        return _rows(x).mean(0).tolist()

    return avg(a)
