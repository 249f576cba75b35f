"""Helpers of the query modules."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import FactorModel


def rounded(column: Column | str, digits: int = 6) -> Column:
    """Rounded, with negative zero as zero."""
    return F.round(F.col(column) if isinstance(column, str) else column, digits) + F.lit(0.0)


def quotient(a: Column, b: Column) -> Column:
    """Division by the rules of floating-point numbers, as in the SQL: by zero it gives an infinity or NaN, not an error."""
    return F.when(b != 0, a / b).otherwise(a * F.pow(b, F.lit(-1.0)))


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


def long_factors(model: FactorModel, digits: int = 6) -> DataFrame:
    """(mode, idx, component, value) of a model."""
    entries = model.factors.select("mode", "idx", F.posexplode("f").alias("component", "value"))
    return entries.select("mode", "idx", "component", rounded("value", digits).alias("value"))


def traced(history: list[dict], spark, **extra) -> DataFrame:
    some = lambda value: None if value is None else float(value)
    rows = [(h["method"], h["iter"], float(h["seconds"]), some(h["loss"]), float(h["train_rmse"]), some(h["rmse"]), h["cold"], h["exchanges"], h["status"]) for h in history]
    frame = spark.createDataFrame(rows, "method string, iter int, seconds double, loss double, train_rmse double, rmse double, cold long, exchanges long, status string")
    for name, value in extra.items():
        frame = frame.withColumn(name, F.lit(value))
    return frame
