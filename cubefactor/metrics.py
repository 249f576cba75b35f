"""Accuracy and loss."""

from __future__ import annotations


from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .model import FactorModel, dot
from .operators.tensor import TensorFrame, mode_counts


def rmse(model: FactorModel, test: DataFrame) -> float:
    error = F.col("x") - F.col("prediction")
    return model.predict(test).agg(F.sqrt(F.avg(error * error))).first()[0]


def report(model: FactorModel, test: DataFrame) -> DataFrame:
    """One row: cells, RMSE, MAE, R squared, normalised squared error."""
    error = F.col("x") - F.col("prediction")
    scored = model.predict(test)
    return scored.agg(
        F.count("*").alias("cells"),
        F.sqrt(F.avg(error * error)).alias("rmse"),
        F.avg(F.abs(error)).alias("mae"),
        (1 - F.sum(error * error) / (F.var_pop("x") * F.count("*"))).alias("r2"),
        (F.sum(error * error) / F.sum(F.col("x") * F.col("x"))).alias("nmse"),
    )


def cold_cells(train: TensorFrame, test: DataFrame) -> int:
    """Held-out cells with a row, in any mode, that has no training cell."""
    warm = test
    for m in train.modes:
        warm = warm.join(train.cells.select(m).distinct(), m, "left_semi")
    return test.count() - warm.count()


def squared_error(model: FactorModel, cells: DataFrame) -> DataFrame:
    error = F.col("x") - F.col("prediction")
    return model.predict(cells).agg(F.sum(error * error).alias("error"))


def loss(model: FactorModel, tensor: TensorFrame, lam: float, reg: str = "plain") -> DataFrame:
    """One row (error, penalty, loss): squared error over observed cells plus the penalty of all factors.

    With `weighted` each row's penalty counts as often as the row has cells.
    """
    rows = model.factors.select("mode", "idx", dot(F.col("f"), F.col("f")).alias("q"))
    if reg == "weighted":
        counts = mode_counts(tensor)
        rows = rows.join(counts, ["mode", "idx"], "left").select((F.col("q") * F.coalesce("nnz", F.lit(0))).alias("q"))
    penalty = rows.agg((F.sum("q") * F.lit(float(lam))).alias("penalty"))
    return squared_error(model, tensor.cells).crossJoin(penalty).select("error", "penalty", (F.col("error") + F.col("penalty")).alias("loss"))


def precision_at_k(ranked: DataFrame, relevant: DataFrame, key: str, item: str, k: int) -> DataFrame:
    """One row: mean share of relevant items among each key's first k."""
    hits = ranked.where(F.col("rank") <= k).join(relevant.select(key, item).distinct().withColumn("_hit", F.lit(1)), [key, item], "left")
    return hits.groupBy(key).agg((F.sum(F.coalesce("_hit", F.lit(0))) / k).alias("p")).agg(F.avg("p").alias("precision"))


