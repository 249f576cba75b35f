"""How updated slices reach the next step."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import planner
from .lineage import written


def publish(part: DataFrame, length: int, exchange: str) -> DataFrame:
    """A slice (idx, a) cut off from the plan that made it, with a row for every index (zeros where no cell is).

    `broadcast` takes the slice through the driver, for slices that the planner found small, if it has few rows;
    else it is written to the shared folder, where the write's commit marks it as complete.
    """
    spark = part.sparkSession
    if exchange == "broadcast" and length <= planner.PLAIN_ROWS:
        got = part.toArrow()
        return spark.createDataFrame(got) if got.num_rows else written(part, "slice")
    return written(part, "slice")


def all_rows(part: DataFrame, length: int, width: int) -> DataFrame:
    """The slice with zero rows for the indices that have no cell."""
    spark = part.sparkSession
    zero = F.array(*[F.lit(0.0)] * width)
    every = spark.range(length).withColumnRenamed("id", "_every")
    return every.join(part, F.col("_every") == F.col("idx"), "left").select(F.col("_every").alias("idx"), F.coalesce("a", zero).alias("a"))
