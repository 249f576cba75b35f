"""The two gradient baselines: averaged replicas, and strata of row-disjoint blocks.

Within a machine gradient steps are sequential, so cells are walked in Arrow batches; across machines the two
methods differ. Averaging lets every replica move all parameters and then takes their mean. Strata let
machines move disjoint parameters, so nothing is averaged, at the price of one exchange per stratum.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from ..functions.init import hash_factors
from ..functions.schedule import inverse_time
from ..model import FactorModel
from ..operators.layout import assign, block, lengths, with_blocks
from ..operators.lineage import written
from ..operators.tensor import TensorFrame, mode_counts
from ..plans import planner
from .base import Solver

ROWS = "mode int, idx long, f array<double>"


def conflict_free(index: np.ndarray) -> np.ndarray:
    """Level of each cell: one more than the highest level of an earlier cell that shares a row with it.

    Cells of a level share no row, so they move at once; level after level gives what one cell after another gives.
    """
    reached: list[dict[int, int]] = [{} for _ in range(index.shape[1])]
    out = np.empty(len(index), np.int64)
    for k, at in enumerate(index.tolist()):
        level = 1 + max(seen.get(i, -1) for seen, i in zip(reached, at, strict=True))
        for seen, i in zip(reached, at, strict=True):
            seen[i] = level
        out[k] = level
    return out


def sgd_cells(index: np.ndarray, x: np.ndarray, factors: list[np.ndarray], counts: list[np.ndarray] | None, lam: float, eta: float, loo: str = "prefix_suffix") -> None:
    """One pass over cells in order: all parameters of a cell move against the gradient of its squared error
    and of its share of the penalty. `index` has a line of positions per cell. With `counts` the penalty of a
    row is shared among its cells; without, its weight by count cancels that share.

    Cells are worked through in levels that share no row, with the result of the order given.
    `loo='divide'` divides the whole product by the own factor, as an ablation; it is undefined at zero.
    """
    if not len(index):
        return
    n_modes = len(factors)
    level = conflict_free(index)
    order = np.argsort(level, kind="stable")
    edges = np.searchsorted(level[order], np.arange(int(level.max()) + 2))
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist()):
        own = order[a:b]
        at = index[own]
        rows = [factors[n][at[:, n]] for n in range(n_modes)]
        whole = rows[0].copy()
        for r in rows[1:]:
            whole *= r
        error = (x[own] - whole.sum(1))[:, None]
        if loo == "divide":
            others = [whole / r for r in rows]
        else:
            before, others = np.ones_like(whole), []
            after = [np.ones_like(whole)]
            for r in reversed(rows[1:]):
                after.append(after[-1] * r)
            for n in range(n_modes):
                others.append(before * after[n_modes - 1 - n])
                before = before * rows[n]
        for n in range(n_modes):
            share = lam if counts is None else (lam / np.maximum(counts[n][at[:, n]], 1))[:, None]
            factors[n][at[:, n]] = rows[n] + 2 * eta * (error * others[n] - share * rows[n])


def _arrays(table: pa.Table, dims: list[int], rank: int) -> list[np.ndarray]:
    out = [np.zeros((d, rank)) for d in dims]
    mode, idx = np.asarray(table.column("mode")), np.asarray(table.column("idx"))
    f = np.asarray(table.column("f").combine_chunks().flatten()).reshape(-1, rank)
    for n in range(len(dims)):
        mine = mode == n + 1
        out[n][idx[mine]] = f[mine]
    return out


@dataclass
class GradientSolver(Solver):
    eta0: float = 0.01
    init: str = "random"
    loo: str = "prefix_suffix"

    def _start(self, tensor: TensorFrame) -> DataFrame:
        """Random starts in all modes, scaled so that products stay of the order of one."""
        scale = 1 / np.sqrt(self.rank)
        return hash_factors(tensor.cells.sparkSession, tensor.dims, self.rank, self.seed).withColumn("f", F.transform("f", lambda v: (v + 0.1) * F.lit(float(scale))))

    def _with_counts(self, cells: DataFrame, tensor: TensorFrame) -> DataFrame:
        """Cells with the cell count of each of their rows (n1..nN), for the plain penalty, which rows share among them."""
        if self.reg == "weighted":
            return cells
        counts = mode_counts(tensor)
        for n, (m, d) in enumerate(zip(tensor.modes, tensor.dims, strict=True), 1):
            side = counts.where(F.col("mode") == n).select(F.col("idx").alias("_i"), F.col("nnz").alias(f"n{n}"))
            cells = cells.join(F.broadcast(side) if planner.fits_broadcast(d, 2) else side, F.col(m) == F.col("_i")).drop("_i")
        return cells

    def _columns(self, n_modes: int) -> list[str]:
        return [f"i{n}" for n in range(1, n_modes + 1)] + ["x"] + ([] if self.reg == "weighted" else [f"n{n}" for n in range(1, n_modes + 1)])

    def _publish(self, factors: DataFrame, dims: list[int]) -> DataFrame:
        if planner.choose_exchange(dims, self.rank) == "broadcast":
            return factors.sparkSession.createDataFrame(factors.toArrow(), ROWS)
        return written(factors, "sgd-factors")


def _row_counts(index: np.ndarray, counts: list[np.ndarray], sizes: list[int]) -> list[np.ndarray]:
    """Counts by position, of the rows that the cells name."""
    out = [np.ones(size) for size in sizes]
    for n, own in enumerate(out):
        own[index[:, n]] = counts[n]
    return out


@dataclass
class AveragedSGD(GradientSolver):
    """Cells are dealt to `machines` replicas at random; parameters are averaged after each iteration.

    `average='touched'` averages a row over the replicas that hold a cell of it. Row assignment has no use here.
    Every replica holds all parameters, so a run whose parameters exceed what a machine may hold is refused.
    """

    average: str = "uniform"
    assignment: str = "none"
    split: str = "once"

    method = "averaged_sgd"

    def __post_init__(self) -> None:
        super().__post_init__()
        if self.assignment == "greedy":
            raise ValueError("replicas own no rows: greedy assignment does not apply")

    def fit(self, tensor: TensorFrame, test: DataFrame | None = None, trace: bool = False) -> FactorModel:
        dims, rank, lam, average, loo, weighted = tensor.dims, self.rank, self.reg_param, self.average, self.loo, self.reg == "weighted"
        if not planner.fits_driver(sum(dims), rank):
            raise MemoryError(f"oom: every replica would hold {sum(dims)} rows of {rank} parameters")
        context = tensor.cells.sparkSession.sparkContext
        factors = self._publish(self._start(tensor), dims)
        source, columns = self._with_counts(tensor.cells, tensor), self._columns(tensor.n_modes)

        def dealt(salt: int) -> DataFrame:
            replica = F.pmod(F.xxhash64(*tensor.modes, F.lit(self.seed + salt)), F.lit(self.machines)).cast("int")
            order = F.xxhash64(*tensor.modes, F.lit(self.seed + salt + 1))
            return source.withColumn("replica", replica).repartitionById(self.machines, "replica").sortWithinPartitions(order).persist(StorageLevel.DISK_ONLY)

        cells = dealt(0)
        history, began = [], time.time()
        for iteration in range(1, self.outer_iters + 1):
            if self.split == "per_iter" and iteration > 1:
                cells.unpersist()
                cells = dealt(iteration)
            eta = inverse_time(self.eta0, iteration)
            shared = context.broadcast(_arrays(factors.toArrow(), dims, rank))  # every replica needs all parameters; checked above

            def replicate(batches: Iterator[pa.RecordBatch], shared=shared, eta=eta) -> Iterator[pa.RecordBatch]:
                own = [a.copy() for a in shared.value]
                touched = [np.zeros(len(a), bool) for a in own]
                some = False
                for batch in batches:
                    some = some or batch.num_rows > 0
                    index = np.column_stack([np.asarray(batch.column(n)) for n in range(len(own))])
                    counts = None if weighted else _row_counts(index, [np.asarray(batch.column(len(own) + 1 + n)) for n in range(len(own))], [len(a) for a in own])
                    sgd_cells(index, np.asarray(batch.column(len(own))), own, counts, lam, eta, loo)
                    for n in range(len(own)):
                        touched[n][index[:, n]] = True
                for n, rows in enumerate(own):
                    keep = np.flatnonzero(touched[n]) if average == "touched" else np.arange(len(rows)) if some else np.zeros(0, int)
                    if len(keep):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keep), n + 1, np.int32)), pa.array(keep), pa.array(list(rows[keep]), pa.list_(pa.float64()))], ["mode", "idx", "f"])

            moved = cells.select(*columns).mapInArrow(replicate, ROWS)
            mean = average_replicas(moved, rank)
            joined = factors.join(mean.withColumnRenamed("f", "g"), ["mode", "idx"], "left").select("mode", "idx", F.coalesce("g", "f").alias("f"))
            factors = self._publish(joined, dims)
            if trace or iteration == self.outer_iters:
                model = FactorModel(factors, rank, dims, history)
                if trace:
                    history.append(self.trace_entry(iteration, began, model, tensor, test))
        cells.unpersist()
        return model


def average_replicas(rows: DataFrame, rank: int) -> DataFrame:
    """The mean of each row's replicas, component by component: partial sums before the shuffle."""
    return rows.groupBy("mode", "idx").agg(F.array(*(F.avg(F.get("f", F.lit(k))) for k in range(rank))).alias("f"))


@dataclass
class StratifiedSGD(GradientSolver):
    """Strata of `machines` blocks that share no row; each stratum's machines move their own rows only.

    Blocks are the machines that `assignment` gives the rows. A stratum costs an exchange of all factor blocks
    but those of mode 1, and there are machines ** (modes - 1) strata: beyond `most_strata` the run is refused
    unless `force`.
    """

    stratum_order: str = "random"
    most_strata: int = 400
    force: bool = False

    method = "stratified_sgd"

    def fit(self, tensor: TensorFrame, test: DataFrame | None = None, trace: bool = False) -> FactorModel:
        dims, rank, lam, m, loo, n_modes, weighted = tensor.dims, self.rank, self.reg_param, self.machines, self.loo, tensor.n_modes, self.reg == "weighted"
        total = m ** (n_modes - 1)
        if total > self.most_strata and not self.force:
            raise RuntimeError(f"oot: {total} strata per iteration would not end in time; force=True runs them all the same")
        assigned = assign(tensor, m, self.assignment, self.seed).select("mode", "idx", "machine").persist()
        blocks = with_blocks(TensorFrame(self._with_counts(tensor.cells, tensor), dims), m, assigned)
        cells = blocks.withColumn("machine", F.col("b1")).repartitionById(m, "machine").sortWithinPartitions("stratum").persist(StorageLevel.DISK_ONLY)
        columns = self._columns(n_modes)
        homes = assigned.withColumnRenamed("machine", "home")
        homes = F.broadcast(homes) if planner.fits_broadcast(sum(dims), 3) else homes
        factors = self._publish(self._start(tensor), dims)

        def step(eta: float):
            def move(key, left: pa.Table, right: pa.Table) -> pa.Table:
                mode, idx = np.asarray(right.column("mode")), np.asarray(right.column("idx"))
                f = np.asarray(right.column("f").combine_chunks().flatten()).reshape(-1, rank).copy() if right.num_rows else np.zeros((0, rank))
                own, places, held = [], [], []
                for n in range(n_modes):
                    mine = np.flatnonzero(mode == n + 1)
                    mine = mine[np.argsort(idx[mine])]
                    own.append(f[mine])
                    held.append(mine)
                    if left.num_rows:
                        places.append(np.searchsorted(idx[mine], np.asarray(left.column(f"i{n + 1}"))))
                if left.num_rows:
                    index = np.column_stack(places)
                    order = np.lexsort(index.T[::-1])  # a fixed order first, then a shuffle of it
                    order = order[np.random.default_rng(len(order)).permutation(len(order))]
                    local = None if weighted else _row_counts(index, [np.asarray(left.column(f"n{n + 1}")) for n in range(n_modes)], [len(h) for h in held])
                    sgd_cells(index[order], np.asarray(left.column("x"))[order], own, local, lam, eta, loo)
                for h, rows in zip(held, own, strict=True):
                    f[h] = rows
                return pa.table({"mode": pa.array(mode, pa.int32()), "idx": pa.array(idx, pa.int64()), "f": pa.array(list(f), pa.list_(pa.float64()))})

            return move

        history, began = [], time.time()
        for iteration in range(1, self.outer_iters + 1):
            eta = inverse_time(self.eta0, iteration)
            order = list(range(total))
            if self.stratum_order == "random":
                np.random.default_rng(self.seed + iteration).shuffle(order)
            for stratum in order:
                shifts = [0] + [stratum // m ** (n_modes - n) % m for n in range(2, n_modes + 1)]
                shift = F.element_at(F.array(*map(F.lit, shifts)), F.col("mode"))
                home = F.coalesce("home", block(F.col("idx"), lengths(dims), m))  # a row without cells stays where its range lies
                placed = factors.join(homes, ["mode", "idx"], "left").select("mode", "idx", "f", F.pmod(home - shift, F.lit(m)).cast("int").alias("machine"))
                part = cells.where(F.col("stratum") == stratum).select("machine", *columns)
                factors = self._publish(part.groupBy("machine").cogroup(placed.groupBy("machine")).applyInArrow(step(eta), ROWS), dims)
            if trace or iteration == self.outer_iters:
                model = FactorModel(factors, rank, dims, history)
                if trace:
                    history.append(self.trace_entry(iteration, began, model, tensor, test))
        cells.unpersist()
        assigned.unpersist()
        return model
