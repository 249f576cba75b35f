"""A tensor as temporary views, for users of SQL."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions import udfs, udtf
from ..operators.tensor import TensorFrame, mode_counts


def register(spark: SparkSession, tensor: TensorFrame, name: str) -> list[str]:
    """Views `name` (cells), `name`_counts (mode, idx, nnz) and, where keys are known, `name`_keys (mode, idx, key as text),
    and the SQL functions. Returns the views' names; views of these names are replaced."""
    tensor.cells.createOrReplaceTempView(name)
    mode_counts(tensor).createOrReplaceTempView(f"{name}_counts")
    made = [name, f"{name}_counts"]
    if tensor.dictionaries:
        parts = [d.select(F.lit(n).alias("mode"), "idx", F.col("key").cast("string").alias("key")) for n, d in enumerate(tensor.dictionaries, 1)]
        reduce(lambda a, b: a.unionByName(b), parts).createOrReplaceTempView(f"{name}_keys")
        made.append(f"{name}_keys")
    udfs.register(spark)
    udtf.register(spark)
    return made
