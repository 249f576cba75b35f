"""A fitted factorization: predictions, ranking, neighbours, fold-in, storage."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.kernels import attach, attach_checked, component_products, normal_equations, predict_expr, solve_rows

#: Bytes of item factors that one pass of a ranking sends to all tasks.
TILE_BYTES = 64 << 20


def dot(left: Column, right: Column) -> Column:
    return F.aggregate(F.zip_with(left, right, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def norm(array: Column) -> Column:
    return F.sqrt(dot(array, array))


def best_of(weights: np.ndarray, items: np.ndarray, names: np.ndarray, seen: list[list[int]], k: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Names and scores of the k best items of each line of weights, by score, then by name; seen ones are left out."""
    for scores, known in zip(weights @ items.T, seen, strict=True):
        if known:
            scores = np.where(np.isin(names, known), -np.inf, scores)
        if len(scores) > k:
            least = np.partition(scores, -k)[-k]
            chosen = np.flatnonzero(scores >= least)
        else:
            chosen = np.arange(len(scores))
        chosen = chosen[np.lexsort((names[chosen], -scores[chosen]))][:k]
        chosen = chosen[scores[chosen] > -np.inf]
        yield names[chosen], scores[chosen]


@dataclass
class FactorModel:
    """Factors (mode, idx, f) with the rank and mode lengths; `trace` has one entry per outer iteration."""

    factors: DataFrame
    rank: int
    dims: list[int]
    trace: list[dict] = field(default_factory=list)

    def slices(self) -> list[DataFrame]:
        return [self.factors.where(F.col("mode") == n).select("idx", F.col("f").alias("a")) for n in range(1, len(self.dims) + 1)]

    def attach(self, cells: DataFrame, prefix: str, modes: list[int] | None = None) -> DataFrame:
        """Cells with the factor rows of the modes; a long mode is joined by a shuffle."""
        return attach_checked(cells, self.slices(), prefix, self.rank, self.dims, modes)

    def predict(self, cells: DataFrame, low: float | None = None, high: float | None = None, broadcast: bool | None = None) -> DataFrame:
        """Cells with `prediction`; a cell with an unknown row gets zero; clipped to [low, high] if given."""
        joined = self.attach(cells, "_f") if broadcast is None else attach(cells, self.slices(), "_f", broadcast)
        names = [f"_f{n}" for n in range(1, len(self.dims) + 1)]
        value = F.coalesce(predict_expr(names, self.rank), F.lit(0.0))
        if low is not None:
            value = F.greatest(value, F.lit(float(low)))
        if high is not None:
            value = F.least(value, F.lit(float(high)))
        return joined.withColumn("prediction", value).drop(*names)

    def recommend(self, users: DataFrame, mode: int, k: int, fixed: dict[int, int], seen: DataFrame | None = None, tile_bytes: int = TILE_BYTES) -> DataFrame:
        """The k best indices of `mode` for each row of `users` (i1, and other modes neither fixed nor `mode`); a top-k report.

        Rows of `users` count once. Items go to the tasks in tiles of bounded size; a task keeps the k best of a
        tile for each of its rows, so the grid of rows and items is never made.
        """
        spark = users.sparkSession
        others = [n for n in range(1, len(self.dims) + 1) if n != mode]
        keys = [f"i{n}" for n in others if n not in fixed and f"i{n}" in users.columns]
        asked = users.select(*keys).distinct()
        if seen is not None:
            known = seen.select(*(F.col(key).alias(f"_{key}") for key in keys), f"i{mode}").groupBy(*(f"_{key}" for key in keys)).agg(F.collect_set(f"i{mode}").alias("_known"))
            hit = F.lit(True)
            for key in keys:
                hit = hit & (F.col(key) == F.col(f"_{key}"))
            asked = asked.join(known, hit, "left").select(*keys, F.coalesce("_known", F.array().cast("array<long>")).alias("_known"))
        else:
            asked = asked.withColumn("_known", F.array().cast("array<long>"))
        for n, idx in fixed.items():
            asked = asked.withColumn(f"i{n}", F.lit(idx).cast("long"))
        joined = self.attach(asked, "_f", others)
        weight = F.array(*(F.coalesce(c, F.lit(0.0)) for c in component_products([F.col(f"_f{n}") for n in others], self.rank)))
        rows = joined.select(*(c for c in asked.columns if c != "_known"), "_known", weight.alias("_w"))
        plain = [c for c in rows.columns if not c.startswith("_")]
        schema = ", ".join(f"{c} long" for c in plain) + f", i{mode} long, prediction double"
        items, length, rank = self.slices()[mode - 1], self.dims[mode - 1], self.rank
        step = max(1, tile_bytes // (8 * (rank + 1)))
        found = None
        for begin in range(0, length, step):
            table = items.where((F.col("idx") >= begin) & (F.col("idx") < begin + step)).toArrow()  # one tile, of bounded size
            names = np.asarray(table.column("idx").combine_chunks()) if table.num_rows else np.zeros(0, np.int64)
            values = np.asarray(table.column("a").combine_chunks().flatten()).reshape(-1, rank) if table.num_rows else np.zeros((0, rank))
            tile = spark.sparkContext.broadcast((names, values))

            def rank_tile(batches: Iterator[pa.RecordBatch], tile=tile) -> Iterator[pa.RecordBatch]:
                own, factors = tile.value
                for batch in batches:
                    for at in range(0, batch.num_rows, 256):
                        part = batch.slice(at, 256)
                        weights = np.asarray(part.column(len(plain) + 1).flatten()).reshape(-1, rank)
                        best = list(best_of(weights, factors, own, part.column(len(plain)).to_pylist(), k))
                        which = pa.array(np.repeat(np.arange(len(best)), [len(i) for i, _ in best]))
                        columns = [pa.array(np.concatenate([b[c] for b in best])) for c in (0, 1)]
                        yield pa.RecordBatch.from_arrays([*(part.column(c).take(which) for c in range(len(plain))), *columns], [*plain, f"i{mode}", "prediction"])

            tops = rows.mapInArrow(rank_tile, schema)
            found = tops if found is None else found.unionByName(tops)
        ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("prediction"), f"i{mode}")))
        return ranked.where(F.col("rank") <= k)

    def similar(self, mode: int, idx: int, k: int) -> DataFrame:
        """The k rows of a mode nearest by cosine in factor space; an unknown row has none."""
        rows = self.slices()[mode - 1]
        one = rows.where(F.col("idx") == idx).select(F.col("a").alias("q"))  # a single row
        scored = rows.where(F.col("idx") != idx).crossJoin(F.broadcast(one))
        return scored.select("idx", (dot(F.col("a"), F.col("q")) / (norm(F.col("a")) * norm(F.col("q")))).alias("cosine")).orderBy(F.desc("cosine"), "idx").limit(k)

    def components(self, mode: int, k: int) -> DataFrame:
        """The k largest entries of each component of a mode."""
        entries = self.slices()[mode - 1].select("idx", F.posexplode("a").alias("component", "value"))
        return entries.withColumn("rank", F.row_number().over(Window.partitionBy("component").orderBy(F.desc("value"), "idx"))).where(F.col("rank") <= k)

    def fold_in(self, cells: DataFrame, mode: int, lam: float, reg: str = "weighted") -> DataFrame:
        """(idx, a): rows of a mode solved from their cells with the other modes' factors fixed."""
        names = [f"_f{n}" for n in range(1, len(self.dims) + 1)]
        joined = self.attach(cells, "_f", [n for n in range(1, len(self.dims) + 1) if n != mode])
        return solve_rows(normal_equations(joined, mode, self.rank, names, F.col("x"), [f"i{mode}"]), self.rank, lam, reg, f"i{mode}")

    def register(self, spark: SparkSession, name: str) -> None:
        """Temporary view `name` (mode, idx, component, value) and SQL function `name`_dot of two factor rows."""
        from .functions.udfs import arrow_dot

        self.factors.select("mode", "idx", F.posexplode("f").alias("component", "value")).createOrReplaceTempView(name)
        spark.udf.register(f"{name}_dot", arrow_dot)

    def save(self, path: str) -> None:
        """Parquet partitioned by mode, with rank and lengths beside it."""
        self.factors.write.partitionBy("mode").parquet(f"{path}/factors")
        spark = self.factors.sparkSession
        spark.createDataFrame([(self.rank, self.dims)], "rank int, dims array<long>").write.parquet(f"{path}/about")

    @staticmethod
    def load(spark: SparkSession, path: str) -> FactorModel:
        about = spark.read.parquet(f"{path}/about").first()
        factors = spark.read.parquet(f"{path}/factors").select("mode", "idx", "f")
        return FactorModel(factors, about["rank"], list(about["dims"]))
