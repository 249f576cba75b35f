"""The steps that all solvers share, as expressions and joins over cells and factor slices."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import planner


#: Rows of a slice that a broadcast holds as one: a power of two.
SHIFT = 8
PACK = 1 << SHIFT


def product(columns: list[Column]) -> Column:
    return reduce(lambda a, b: a * b, columns, F.lit(1.0)) if columns else F.lit(1.0)


def component_products(arrays: list[Column], width: int) -> list[Column]:
    """Per component, the product over the given modes' slice arrays."""
    return [product([F.get(a, F.lit(k)) for a in arrays]) for k in range(width)]


def leave_one_out(names: list[str], mode: int, width: int) -> list[Column]:
    """Per component, the product over all modes but one; `names` are the slice columns in mode order."""
    return component_products([F.col(c) for n, c in enumerate(names, 1) if n != mode], width)


def predict_expr(names: list[str], width: int) -> Column:
    """The sum over components of the products over all modes."""
    return reduce(lambda a, b: a + b, component_products([F.col(c) for c in names], width))


def packed(part: DataFrame) -> DataFrame:
    """(block, n, v): a slice by blocks of PACK consecutive rows, v holding the n components of one row after another.

    A hash entry and its headers take more memory than a row's few numbers, on the driver above all, where broadcasts
    are built: a block has one entry for all of its rows. It costs a shuffle of the slice. Rows missing in a block hold nulls.
    """
    rows = part.groupBy(F.shiftright("idx", SHIFT).alias("block")).agg(F.max(F.size("a")).alias("n"), F.sort_array(F.collect_list(F.struct(F.pmod("idx", F.lit(PACK)).cast("int").alias("p"), "a"))).alias("s"))
    last = F.get("s", F.size("s") - 1)["p"]
    absent = F.array_repeat(F.lit(None).cast("double"), F.col("n"))
    filled = F.transform(F.sequence(F.lit(0), last), lambda p: F.coalesce(F.get(F.filter("s", lambda s: s["p"] == p), F.lit(0))["a"], absent))
    return rows.select("block", "n", F.flatten(F.when(last + 1 == F.size("s"), F.transform("s", lambda s: s["a"])).otherwise(filled)).alias("v"))


def attach(cells: DataFrame, slices: list[DataFrame], prefix: str = "a", broadcast: bool | int | str | list[bool | str] = True, modes: list[int] | None = None) -> DataFrame:
    """Cells with the slice array of each mode as `prefix`n. Slices hold (idx, a); missing rows leave null.

    With `packed` as `broadcast`, slices are broadcast by blocks of rows. A number above one cuts each packed slice
    into so many tiles, broadcast one by one: the cells stay where they are although the slice as a whole is too
    large for one broadcast. A list has the form of each mode's slice.
    """
    forms = broadcast if isinstance(broadcast, list) else [broadcast] * len(slices)
    for n, (part, broadcast) in enumerate(zip(slices, forms, strict=True), 1):
        if modes is not None and n not in modes:
            continue
        name, at, index = f"{prefix}{n}", f"_{prefix}{n}", F.col(f"i{n}")
        if broadcast in (True, False, 0, 1):
            side = part.select(F.col("idx").alias(at), F.col("a").alias(name))
            cells = cells.join(F.broadcast(side) if broadcast else side, index == F.col(at), "left").drop(at)
            continue
        blocks = packed(part).select(F.col("block").alias(at), F.col("n").alias(f"{at}n"), F.col("v").alias(f"{at}v"))
        count = 1 if broadcast == "packed" else broadcast
        tiles = [f"_{name}_{t}" for t in range(count)]
        row = F.slice(f"{at}v", F.pmod(index, F.lit(PACK)).cast("int") * F.col(f"{at}n") + 1, F.col(f"{at}n"))
        for t, tile in enumerate(tiles):
            side = blocks.where(F.pmod(at, F.lit(count)) == t) if count > 1 else blocks
            cells = cells.join(F.broadcast(side), F.shiftright(index, SHIFT) == F.col(at), "left").withColumn(tile, row).drop(at, f"{at}n", f"{at}v")
        cells = cells.withColumn(name, F.coalesce(*tiles)).drop(*tiles)
    return cells


def attach_checked(cells: DataFrame, slices: list[DataFrame], prefix: str, width: int, dims: list[int], modes: list[int] | None = None) -> DataFrame:
    """The same, each slice broadcast only where its size is within the limit, else joined with a shuffle."""
    for n, length in enumerate(dims, 1):
        if modes is None or n in modes:
            cells = attach(cells, slices, prefix, planner.broadcast_form(length, width + 1), [n])
    return cells


def add_back_group(width: int, n_modes: int, residual: str = "r", prefix: str = "a") -> Column:
    """Group residual: the residual plus the group's contribution."""
    return F.col(residual) + predict_expr([f"{prefix}{n}" for n in range(1, n_modes + 1)], width)


def subtract_group(width: int, n_modes: int, residual: str = "rhat", prefix: str = "a") -> Column:
    """New residual: the group residual minus the group's new contribution."""
    return F.col(residual) - predict_expr([f"{prefix}{n}" for n in range(1, n_modes + 1)], width)


def normal_sums(target: Column, others: list[Column]) -> list[Column]:
    """The sums of a row's normal equations: packed upper triangle, right side, and cell count."""
    width = len(others)
    gram = [F.sum(others[a] * others[b]).alias(f"g{a}_{b}") for a in range(width) for b in range(a, width)]
    right = [F.sum(target * others[a]).alias(f"b{a}") for a in range(width)]
    return [*gram, *right, F.count("*").alias("n")]


def normal_equations(joined: DataFrame, mode: int, width: int, names: list[str], target: Column, by: list[str]) -> DataFrame:
    """Normal equations of every row of a mode: partial and final hash aggregation, or Arrow segments if wide."""
    others = leave_one_out(names, mode, width)
    return joined.groupBy(*by).agg(*normal_sums(target, others))


def normal_equations_arrow(joined: DataFrame, mode: int, width: int, names: list[str], target: Column, by: list[str]) -> DataFrame:
    """The same by segment sums over Arrow batches: partial sums per batch, then one aggregation of arrays.

    Used where the sums would be too many columns for generated code.
    """
    others = leave_one_out(names, mode, width)
    rows = joined.select(*(F.col(b).cast("long").alias(b) for b in by), target.alias("t"), F.array(*others).alias("p"))
    upper = np.triu_indices(width)
    schema = ", ".join(f"{b} long" for b in by) + ", s array<double>"

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows == 0:
                continue
            keys = np.column_stack([np.asarray(batch.column(k)) for k in range(len(by))])
            target_, p = np.asarray(batch.column(len(by))), np.asarray(batch.column(len(by) + 1).flatten()).reshape(-1, width)
            order = np.lexsort(keys.T[::-1])
            keys, target_, p = keys[order], target_[order], p[order]
            first = np.flatnonzero(np.concatenate([[True], (keys[1:] != keys[:-1]).any(1)]))
            sums = np.hstack([np.add.reduceat(p[:, upper[0]] * p[:, upper[1]], first), np.add.reduceat(p * target_[:, None], first), np.diff(np.append(first, len(keys)))[:, None]])
            yield pa.RecordBatch.from_arrays([*(pa.array(keys[first, k]) for k in range(len(by))), pa.array(list(sums), pa.list_(pa.float64()))], [*by, "s"])

    size = width * (width + 1) // 2 + width + 1
    grouped = rows.mapInArrow(partial, schema).groupBy(*by).agg(*(F.sum(F.get("s", F.lit(k))).alias(f"s{k}") for k in range(size)))
    names_ = [f"g{a}_{b}" for a in range(width) for b in range(a, width)] + [f"b{a}" for a in range(width)] + ["n"]
    return grouped.select(*by, *(F.col(f"s{k}").alias(n) for k, n in enumerate(names_)))


def penalty(count: Column, lam: float, reg: str) -> Column:
    return F.lit(float(lam)) * count if reg == "weighted" else F.lit(float(lam))


def solve_rows(equations: DataFrame, width: int, lam: float, reg: str, idx: str = "idx", solver: str = "cholesky") -> DataFrame:
    """(idx, a): the minimiser of each row. One component is a division; more are solved in Arrow batches."""
    if width == 1:
        bottom = F.col("g0_0") + penalty(F.col("n"), lam, reg)
        return equations.select(F.col(idx).cast("long").alias("idx"), F.array(F.when(bottom > 0, F.col("b0") / bottom).otherwise(0.0)).alias("a"))
    columns = [f"g{a}_{b}" for a in range(width) for b in range(a, width)] + [f"b{a}" for a in range(width)] + ["n"]

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                values = np.column_stack([np.asarray(batch.column(k + 1)).astype(float) for k in range(len(columns))])
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(solve_batch(values, width, lam, reg, solver)), pa.list_(pa.float64()))], ["idx", "a"])

    return equations.select(F.col(idx).cast("long").alias("idx"), *(F.col(c).cast("double") for c in columns)).mapInArrow(solve, "idx long, a array<double>")


def solve_batch(values: np.ndarray, width: int, lam: float, reg: str, solver: str = "cholesky") -> np.ndarray:
    """Solutions of packed normal equations, one per line: triangle, right side, count."""
    m = width * (width + 1) // 2
    gram = np.zeros((len(values), width, width))
    upper = np.triu_indices(width)
    gram[:, upper[0], upper[1]] = values[:, :m]
    gram[:, upper[1], upper[0]] = values[:, :m]
    weight = values[:, -1] if reg == "weighted" else np.ones(len(values))
    gram += (lam * weight)[:, None, None] * np.eye(width)
    right = values[:, m : m + width]
    if solver == "inverse":
        return np.einsum("nij,nj->ni", np.linalg.inv(gram), right)
    if solver == "cholesky":
        try:
            low = np.linalg.cholesky(gram)
            half = np.linalg.solve(low, right[:, :, None])
            return np.linalg.solve(np.swapaxes(low, 1, 2), half)[:, :, 0]
        except np.linalg.LinAlgError:
            pass  # a singular system: fall through to least squares, row by row
    return np.stack([np.linalg.lstsq(g, r, rcond=None)[0] for g, r in zip(gram, right, strict=True)])
