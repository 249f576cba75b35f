"""Reading the star-schema tables, and sparse tensors as delimited text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.lineage import ship_package


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def coo_schema(n_modes: int, corrupt: bool = False) -> T.StructType:
    fields = [T.StructField(f"i{n}", T.LongType()) for n in range(1, n_modes + 1)] + [T.StructField("x", T.DoubleType())]
    return T.StructType(fields + ([T.StructField("_corrupt", T.StringType())] if corrupt else []))


def read_coo(spark: SparkSession, path: str, n_modes: int, *, sep: str = "\t", one_based: bool = True, fmt: str = "csv") -> DataFrame:
    """Cells from lines of N indices and a value (csv) or from JSON lines; lines that don't parse are dropped.

    `bad_lines` tells how many were dropped.
    """
    reader = spark.read.schema(coo_schema(n_modes, True)).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt")
    raw = reader.option("sep", sep).csv(path) if fmt == "csv" else reader.json(path)
    good = raw.where(F.col("_corrupt").isNull() & F.col("x").isNotNull())
    shift = 1 if one_based else 0
    return good.select(*((F.col(f"i{n}") - shift).alias(f"i{n}") for n in range(1, n_modes + 1)), "x")


def bad_lines(spark: SparkSession, path: str, n_modes: int, *, sep: str = "\t") -> int:
    """How many lines of a delimited file are no cells."""
    parts = F.split("value", sep)
    fine = (F.size(parts) == n_modes + 1) & F.forall(parts, lambda p: p.try_cast("double").isNotNull())
    return spark.read.text(path).where(~fine).count()


def write_coo(cells: DataFrame, path: str, *, sep: str = "\t", one_based: bool = True) -> None:
    """Cells as lines of N indices and a value."""
    shift = 1 if one_based else 0
    modes = [c for c in cells.columns if c.startswith("i") and c[1:].isdigit()]
    cells.select(*((F.col(c) + shift).alias(c) for c in modes), "x").write.option("sep", sep).csv(path)
