"""Starting values of factors as expressions: nothing is stored until a row is first updated."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.tensor import portable


def start_value(idx: Column, mode: int, component: int, seed: int, init: str, scale: float = 1.0) -> Column:
    """`zero_first` starts mode 1 at zero, so that the first residual is the data; `random` starts all modes."""
    if init == "zero_first" and mode == 1:
        return F.lit(0.0)
    return portable(idx, mode, component, seed) * F.lit(scale)


def start_slice(spark: SparkSession, length: int, mode: int, components: list[int], seed: int, init: str, scale: float = 1.0) -> DataFrame:
    """(idx, a): the starting values of some components of a mode."""
    rows = spark.range(length).withColumnRenamed("id", "idx")
    return rows.select("idx", F.array(*(start_value(F.col("idx"), mode, k, seed, init, scale) for k in components)).alias("a"))


def hash_factors(spark: SparkSession, dims: list[int], rank: int, seed: int = 42) -> DataFrame:
    """(mode, idx, f): portable pseudo-random factors of every mode."""
    out = None
    for mode, length in enumerate(dims, 1):
        part = start_slice(spark, length, mode, list(range(rank)), seed, "random").select(F.lit(mode).alias("mode"), "idx", F.col("a").alias("f"))
        out = part if out is None else out.unionByName(part)
    return out
