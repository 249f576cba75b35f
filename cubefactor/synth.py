"""Planted tensors: hash-uniform coordinates, hash-uniform factors, Gaussian noise; nothing is read or stored."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.init import start_slice
from .functions.kernels import attach, predict_expr
from .operators.tensor import TensorFrame


def _uniform(*parts: Column) -> Column:
    return (F.pmod(F.xxhash64(*parts), F.lit(1 << 53)).cast("double") + 0.5) / F.lit(float(1 << 53))


def _noise(sigma: float, *parts: Column) -> Column:
    first, second = _uniform(*parts, F.lit(1)), _uniform(*parts, F.lit(2))
    return F.lit(float(sigma)) * F.sqrt(-2 * F.log(first)) * F.cos(2 * F.pi() * second)


def _values(cells: DataFrame, dims: list[int], rank: int, sigma: float, seed: int) -> DataFrame:
    modes = [f"i{n}" for n in range(1, len(dims) + 1)]
    slices = [start_slice(cells.sparkSession, d, n, list(range(rank)), seed, "random") for n, d in enumerate(dims, 1)]
    joined = attach(cells.select(*modes), slices, "s", broadcast=8 * rank * sum(dims) <= 256 << 20)
    value = predict_expr([f"s{n}" for n in range(1, len(dims) + 1)], rank)
    return joined.select(*modes, (value + _noise(sigma, *(F.col(m) for m in modes), F.lit(seed))).alias("x"))


def planted(spark: SparkSession, dims: list[int], nnz: int, rank: int, sigma: float = 0.01, seed: int = 42) -> TensorFrame:
    """About `nnz` cells (coordinates that meet twice count once) of a tensor of known rank."""
    places = [F.pmod(F.xxhash64("id", F.lit(n), F.lit(seed)), F.lit(d)).alias(f"i{n}") for n, d in enumerate(dims, 1)]
    return TensorFrame(_values(spark.range(nnz).select(*places).distinct(), dims, rank, sigma, seed), list(dims))


def planted_on(tensor: TensorFrame, rank: int, sigma: float = 0.01, seed: int = 42) -> TensorFrame:
    """The coordinates of a tensor with planted values."""
    return TensorFrame(_values(tensor.cells, tensor.dims, rank, sigma, seed), tensor.dims, tensor.dictionaries)


#: The four published scales, for the factor that varies; the others stay at the second (fixed values).
GRID = {"modes": (2, 3, 4, 5), "length": (300, 1000, 3000, 10_000), "cells": (3000, 10_000, 30_000, 100_000), "rank": (3, 10, 30, 100)}
