"""Floors for accuracy: the mean, the mean with a bias per row, and Spark's own matrix solver for two modes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.tensor import TensorFrame


@dataclass
class MeanModel:
    """Predicts the mean of all training cells."""

    mean: float = 0.0

    def fit(self, tensor: TensorFrame) -> MeanModel:
        self.mean = tensor.cells.agg(F.avg("x")).first()[0] or 0.0
        return self

    def predict(self, cells: DataFrame) -> DataFrame:
        return cells.withColumn("prediction", F.lit(float(self.mean)))


@dataclass
class BiasModel:
    """Mean plus each row's mean deviation, shrunk by `shrink` cells."""

    shrink: float = 5.0

    def fit(self, tensor: TensorFrame) -> BiasModel:
        self.mean = tensor.cells.agg(F.avg("x")).first()[0] or 0.0
        self.biases = [tensor.cells.groupBy(m).agg((F.sum(F.col("x") - self.mean) / (F.count("*") + self.shrink)).alias(f"_b{m}")) for m in tensor.modes]
        self.modes = tensor.modes
        return self

    def predict(self, cells: DataFrame) -> DataFrame:
        value = F.lit(float(self.mean))
        for m, bias in zip(self.modes, self.biases, strict=True):
            cells = cells.join(bias, m, "left")
            value = value + F.coalesce(f"_b{m}", F.lit(0.0)) / len(self.modes)
        return cells.withColumn("prediction", value).drop(*(f"_b{m}" for m in self.modes))


def mllib_als(tensor: TensorFrame, rank: int, iterations: int, lam: float, seed: int = 42):
    """Spark's alternating least squares for matrices; a cross-check of full_als with two modes."""
    from pyspark.ml.recommendation import ALS

    cells = tensor.cells.select(F.col("i1").cast("int"), F.col("i2").cast("int"), F.col("x").cast("float"))
    return ALS(rank=rank, maxIter=iterations, regParam=lam, userCol="i1", itemCol="i2", ratingCol="x", seed=seed).fit(cells)
