"""Functions for users of SQL where a built-in form is clumsy: an Arrow scalar function and an aggregate.

The engine's own steps use built-in expressions; these come in batches of Arrow arrays and pandas series.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, pandas_udf
from pyspark.sql.types import DoubleType  # a type's name could be read by a running session only


@arrow_udf(DoubleType())
def arrow_dot(left: pa.Array, right: pa.Array) -> pa.Array:
    """Inner product of two factor rows of equal length; null where either row is null."""
    known = np.asarray(left.is_valid()) & np.asarray(right.is_valid())
    at = pa.array(np.flatnonzero(known))
    out = np.full(len(left), np.nan)
    if len(at):
        a, b = left.take(at), right.take(at)
        products = np.asarray(a.flatten()) * np.asarray(b.flatten())
        bounds = np.asarray(a.offsets)[:-1] - a.offsets[0].as_py()
        full = np.diff(np.asarray(a.offsets)) > 0
        sums = np.zeros(len(at))
        sums[full] = np.add.reduceat(products, bounds[full]) if full.any() else 0
        out[np.asarray(at)] = sums
    return pa.array(out, mask=~known)


@pandas_udf(DoubleType())
def rmse_of(value: pd.Series, prediction: pd.Series) -> float:
    """Root mean square error of a group; a pandas aggregate holds its group, so use it on groups of bounded size."""
    return float(np.sqrt(np.mean((value - prediction) ** 2)))


def register(spark: SparkSession) -> None:
    spark.udf.register("arrow_dot", arrow_dot)
    spark.udf.register("rmse_of", rmse_of)
