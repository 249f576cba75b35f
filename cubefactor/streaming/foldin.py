"""Rows of a mode kept up to date as cells arrive: the normal equations are sums, so batches add up."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import attach_checked, normal_equations, solve_rows
from ..operators.lineage import written


class FoldIn:
    """State of `foreachBatch`: packed sums of every row of a mode seen so far, written after each batch.

    With `state` (a folder beside the query's checkpoint) the sums of each batch are written under its number, and
    a new object goes on from the last one: a batch that is delivered again, also after a restart, is added once.
    Without it the state lives as long as the object.
    """

    def __init__(self, factors: list[DataFrame], mode: int, rank: int, lam: float, reg: str = "weighted", then: Callable[[DataFrame, int], None] | None = None, state: str | None = None) -> None:
        self.factors, self.mode, self.rank, self.lam, self.reg, self.then, self.state = factors, mode, rank, lam, reg, then, state
        self.dims = [f.count() for f in factors]
        self.sums: DataFrame | None = None
        self.last = -1
        if state and factors:
            self._resume()

    def _resume(self) -> None:
        spark = self.factors[0].sparkSession
        try:
            kept = spark.read.parquet(self.state)
        except AnalysisException:  # no batch has been written yet
            return
        last = kept.agg(F.max("batch")).first()[0]
        if last is not None:
            self.last = int(last)
            self.sums = spark.read.parquet(f"{self.state}/batch={self.last}")

    def __call__(self, cells: DataFrame, batch: int) -> None:
        if batch <= self.last:
            return
        n_modes = len(self.factors)
        names = [f"_f{n}" for n in range(1, n_modes + 1)]
        others = [n for n in range(1, n_modes + 1) if n != self.mode]
        joined = attach_checked(cells, self.factors, "_f", self.rank, self.dims, others)
        fresh = normal_equations(joined, self.mode, self.rank, names, F.col("x"), [f"i{self.mode}"])
        both = fresh if self.sums is None else self.sums.unionByName(fresh)
        key = f"i{self.mode}"
        total = both.groupBy(key).agg(*(F.sum(c).alias(c) for c in both.columns if c != key))
        if self.state:
            path = f"{self.state}/batch={batch}"
            total.write.mode("overwrite").parquet(path)  # what a lost attempt left is replaced
            self.sums = cells.sparkSession.read.schema(total.schema).parquet(path)
        else:
            self.sums = written(total, "fold-in")
        self.last = batch
        if self.then:
            self.then(self.rows(), batch)

    def rows(self) -> DataFrame:
        """(idx, a): the rows as solved from all cells so far."""
        return solve_rows(self.sums, self.rank, self.lam, self.reg, f"i{self.mode}")
