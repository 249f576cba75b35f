"""A table function for SQL users: one row per mode of a cell."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="mode: int, idx: long, x: double")
class ModeCopies:
    """Explodes a cell into its mode copies: (mode, idx, x) for each of its indices.

    The engine itself explodes an array of structs, which stays in generated code.
    """

    def eval(self, indices: list, x: float):
        for mode, idx in enumerate(indices or [], 1):
            yield mode, idx, x


def register(spark: SparkSession) -> None:
    spark.udtf.register("mode_copies", ModeCopies)
