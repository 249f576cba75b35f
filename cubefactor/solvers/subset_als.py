"""Least squares by groups of columns: a chosen number of factor columns at a time, all other columns held in the residual.

Each group goes through three kinds of steps. The group's old contribution is added back to the residual; the
rows of one mode after another are solved from their normal equations; the new contribution is subtracted.
Only the group's columns are live, so memory follows the group's width, not the rank. With mode copies every
step reads a partition's own cells: the shuffle that places them is the only one.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from ..functions import kernels
from ..functions.init import start_slice
from ..model import FactorModel
from ..operators.exchange import all_rows, publish
from ..operators.layout import assign, distribute, owners
from ..operators.lineage import written
from ..operators.tensor import TensorFrame
from ..plans import planner
from .base import Solver


@dataclass
class SubsetALS(Solver):
    """`group_width` columns per group; `inner_iters` sweeps over the modes before the next group."""

    group_width: int = 10
    inner_iters: int = 1
    column_order: str = "random"
    storage: str = "mode_copies"
    exchange: str = "auto"
    solver: str = "cholesky"
    kernel: str = "auto"
    checkpoint_every: int = 5
    fused: bool = False
    tiles: int = 0

    method = "subset_als"

    def __post_init__(self) -> None:
        super().__post_init__()
        if not 1 <= self.group_width <= self.rank:
            raise ValueError("group_width must lie between 1 and rank")
        if self.fused and self.group_width != 1:
            raise ValueError("only single columns can be fused")
        if self.storage not in ("mode_copies", "single", "none", "auto"):
            raise ValueError(f"unknown storage {self.storage!r}")

    # -- where the cells are -------------------------------------------------------------------------

    def _place(self, cells: DataFrame, tensor: TensorFrame, assigned: DataFrame | None, storage: str) -> list[DataFrame]:
        """A frame of cells per mode: copies, one shared copy, or the written cells that every step deals out again."""
        if storage == "mode_copies":
            return [distribute(cells, assigned, n, self.machines, tensor.dims[n - 1]) for n in range(1, tensor.n_modes + 1)]
        if storage == "single":
            one = cells.repartition(self.machines, *tensor.modes).persist(StorageLevel.DISK_ONLY)
            return [one] * tensor.n_modes
        return [cells] * tensor.n_modes

    def _dealt(self, placed: DataFrame, assigned: DataFrame | None, mode: int, length: int, storage: str) -> DataFrame:
        """The cells as a step of a mode reads them: without caching, every step sends them to their rows' owners anew."""
        if storage != "none":
            return placed
        return owners(placed, assigned, mode, "machine", length).repartitionById(self.machines, "machine")

    def _spread(self, exchange: str, dims: list[int], width: int) -> bool | int | list[bool | str]:
        """How slices are joined: broadcast, those of long modes packed, in so many packed tiles, or by a shuffle."""
        if exchange in ("broadcast", "dfs"):
            return [planner.broadcast_form(d, width + 1) or "packed" for d in dims]
        return (self.tiles or planner.tile_count(dims, width)) if exchange == "tiles" else False

    def _solve_mode(self, placed: DataFrame, mode: int, slices: list[DataFrame], old: list[DataFrame] | None, width: int, storage: str, small: bool | int | list[bool | str]) -> DataFrame:
        """(idx, a): the rows of a mode. `old` holds the slices before the group where the residual is fused."""
        n_modes = len(slices)
        names = [f"a{n}" for n in range(1, n_modes + 1)]
        others = [n for n in range(1, n_modes + 1) if n != mode]
        joined = kernels.attach(placed, slices, "a", small, others)
        target = F.col("rhat")
        if old is not None:
            joined = kernels.attach(joined, old, "o", small)
            target = kernels.add_back_group(width, n_modes, "r", "o")
        by = [f"i{mode}"] if storage == "single" else ["machine", f"i{mode}"]
        sums = kernels.normal_equations if planner.choose_kernel(width, self.kernel) == "sql" else kernels.normal_equations_arrow
        return kernels.solve_rows(sums(joined, mode, width, names, target, by), width, self.reg_param, self.reg, f"i{mode}", self.solver)

    # -- the run -------------------------------------------------------------------------------------

    def fit(self, tensor: TensorFrame, test: DataFrame | None = None, trace: bool = False) -> FactorModel:
        n_modes, dims = tensor.n_modes, tensor.dims
        spark = tensor.cells.sparkSession
        storage = planner.choose_storage(tensor.cells.count(), dims, self.machines, storage=self.storage) if self.storage == "auto" else self.storage
        exchange = planner.choose_exchange(dims, self.group_width, self.exchange)
        small = self._spread(exchange, dims, self.group_width)
        assigned = assign(tensor, self.machines, self.assignment, self.seed).persist() if storage != "single" else None
        columns: dict[tuple[int, int], DataFrame] = {}  # (mode, column) -> slice of one column, once updated

        def slice_of(mode: int, group: list[int]) -> DataFrame:
            if (mode, group[0]) not in columns:
                return start_slice(spark, dims[mode - 1], mode, group, self.seed, self.init)
            whole, place = columns[mode, group[0]]
            if len(group) == len(place) and all(place.get(k) == j for j, k in enumerate(group)):
                return whole
            part = whole.select("idx", F.array(F.get("a", F.lit(place[group[0]]))).alias("a"))
            for k in group[1:]:
                other, at = columns[mode, k]
                part = part.join(other.select(F.col("idx").alias("_i"), F.get("a", F.lit(at[k])).alias("_v")), F.col("idx") == F.col("_i")).select("idx", F.concat("a", F.array("_v")).alias("a"))
            return publish(part, dims[mode - 1], exchange)

        base = tensor.cells.select(*tensor.modes, "x", F.col("x").alias("r"))
        if self.init == "random":  # the start contributes, so the first residual is not the data
            every = list(range(self.rank))
            starts = [start_slice(spark, d, n, every, self.seed, self.init) for n, d in enumerate(dims, 1)]
            base = kernels.attach(base, starts, "s", small).withColumn("r", F.col("x") - kernels.predict_expr([f"s{n}" for n in range(1, n_modes + 1)], self.rank)).select(*tensor.modes, "x", "r")
        placed = self._place(base, tensor, assigned, storage)
        names = [f"a{n}" for n in range(1, n_modes + 1)]
        history, began, done, last = [], time.time(), 0, None
        for iteration in range(1, self.outer_iters + 1):
            for group in self.column_groups(self.group_width, self.column_order, iteration):
                width = len(group)
                old = [slice_of(n, group) for n in range(1, n_modes + 1)]
                current = list(old)
                if self.fused:
                    work, before = placed, old
                else:
                    work, before = self._rewrite(placed, old, storage, small, lambda w=width: kernels.add_back_group(w, n_modes), "rhat", [*tensor.modes, "x"], n_modes), None
                for _ in range(self.inner_iters):
                    for mode in range(1, n_modes + 1):
                        cells = self._dealt(work[mode - 1], assigned, mode, dims[mode - 1], storage)
                        solved = self._solve_mode(cells, mode, current, before, width, storage, small)
                        current[mode - 1] = publish(all_rows(solved, dims[mode - 1], width), dims[mode - 1], exchange)
                done += 1
                if self.fused:
                    expression = lambda w=width: kernels.add_back_group(w, n_modes, "r", "o") - kernels.predict_expr(names, w)
                    fresh = self._rewrite(placed, current, storage, small, expression, "r", [*tensor.modes, "x"], n_modes, old, last=True)
                else:
                    fresh = self._rewrite(work, current, storage, small, lambda w=width: kernels.subtract_group(w, n_modes), "r", [*tensor.modes, "x"], n_modes, last=True)
                if storage == "mode_copies" and done % self.checkpoint_every == 0:
                    # Lineage ends in the shared folder; the cells are placed anew from there.
                    fresh_base = written(fresh[0].select(*tensor.modes, "x", "r"), "residual")
                    self._release([placed, work, fresh])
                    fresh = self._place(fresh_base, tensor, assigned, storage)
                elif storage != "none":
                    if storage == "mode_copies":
                        for frame in {id(f): f for f in fresh}.values():
                            frame.count()
                    self._release([placed, work] if not self.fused else [placed])
                placed = fresh
                for mode in range(1, n_modes + 1):
                    for k in group:
                        columns[mode, k] = (current[mode - 1], {c: at for at, c in enumerate(group)})
            if trace or self.tol or iteration == self.outer_iters:
                model = FactorModel(self._factors(columns, dims, exchange), self.rank, dims, history)
                if trace or self.tol:
                    history.append(self.trace_entry(iteration, began, model, tensor, test))
                    if self.tol and last is not None and last - history[-1]["train_rmse"] < self.tol:
                        break
                    last = history[-1]["train_rmse"]
        self._release([placed])
        return model

    @staticmethod
    def _release(groups: list[list[DataFrame]]) -> None:
        for frames in groups:
            for frame in {id(f): f for f in frames}.values():
                frame.unpersist()

    def _rewrite(self, placed: list[DataFrame], slices: list[DataFrame], storage: str, small: bool | int | list[bool | str], expression, name: str, keep: list[str], n_modes: int, old: list[DataFrame] | None = None, last: bool = False) -> list[DataFrame]:
        """Every copy with a new residual column; each copy reads its own cells, so copies cannot drift apart.

        One shared copy is written after a group's `last` rewrite: a plan that held the cached plans of all groups
        before it would fill the driver. Copies per mode keep their places, so theirs is cut only at checkpoints.
        """
        out, seen = [], {}
        for frame in placed:
            if id(frame) not in seen:
                joined = kernels.attach(frame, slices, "a", small)
                if old is not None:
                    joined = kernels.attach(joined, old, "o", small)
                extra = ["machine"] if storage == "mode_copies" else []
                fresh = joined.select(*extra, *keep, expression().alias(name))
                seen[id(frame)] = written(fresh, "residual") if storage == "none" or last and storage == "single" else fresh.persist(StorageLevel.DISK_ONLY)
            out.append(seen[id(frame)])
        return out

    def _factors(self, columns: dict, dims: list[int], exchange: str) -> DataFrame:
        """(mode, idx, f) with columns in their own order."""
        parts = None
        for mode in range(1, len(dims) + 1):
            wholes: dict[int, tuple[DataFrame, dict[int, int]]] = {}
            for k in range(self.rank):
                frame, place = columns[mode, k]
                wholes.setdefault(id(frame), (frame, place))
            joined, where = None, {}
            for number, (frame, place) in enumerate(wholes.values()):
                side = frame.select(F.col("idx").alias("_i"), F.col("a").alias(f"_a{number}"))
                joined = side.withColumnRenamed("_i", "idx") if joined is None else joined.join(side, F.col("idx") == F.col("_i")).drop("_i")
                for k, at in place.items():
                    if columns[mode, k][0] is frame:
                        where[k] = F.get(f"_a{number}", F.lit(at))
            part = joined.select(F.lit(mode).alias("mode"), "idx", F.array(*(where[k] for k in range(self.rank))).alias("f"))
            parts = part if parts is None else parts.unionByName(part)
        return written(parts, "factors")


@dataclass
class ColumnCD(SubsetALS):
    """One column at a time: a scalar division per row, no rewrite before the update (fused), least memory."""

    group_width: int = 1
    column_order: str = "fixed"
    fused: bool = True

    method = "column_cd"


@dataclass
class FullALS(SubsetALS):
    """All columns at once: each row of a mode from its whole normal equations. The residual is the data itself."""

    group_width: int = 0

    method = "full_als"

    def __post_init__(self) -> None:
        self.group_width = self.rank
        super().__post_init__()

    def fit(self, tensor: TensorFrame, test: DataFrame | None = None, trace: bool = False) -> FactorModel:
        n_modes, dims = tensor.n_modes, tensor.dims
        spark = tensor.cells.sparkSession
        exchange = planner.choose_exchange(dims, self.rank, self.exchange)
        small = self._spread(exchange, dims, self.rank)
        storage = planner.choose_storage(tensor.cells.count(), dims, self.machines, storage=self.storage) if self.storage == "auto" else self.storage
        assigned = assign(tensor, self.machines, self.assignment, self.seed).persist() if storage != "single" else None
        every = list(range(self.rank))
        current = [start_slice(spark, d, n, every, self.seed, self.init) for n, d in enumerate(dims, 1)]
        placed = self._place(tensor.cells.select(*tensor.modes, "x", F.col("x").alias("rhat")), tensor, assigned, storage)
        history, began, last = [], time.time(), None
        for iteration in range(1, self.outer_iters + 1):
            for _ in range(self.inner_iters):
                for mode in range(1, n_modes + 1):
                    cells = self._dealt(placed[mode - 1], assigned, mode, dims[mode - 1], storage)
                    solved = self._solve_mode(cells, mode, current, None, self.rank, storage, small)
                    current[mode - 1] = publish(all_rows(solved, dims[mode - 1], self.rank), dims[mode - 1], exchange)
            if trace or self.tol or iteration == self.outer_iters:
                parts = None
                for mode, part in enumerate(current, 1):
                    rows = part.select(F.lit(mode).alias("mode"), "idx", F.col("a").alias("f"))
                    parts = rows if parts is None else parts.unionByName(rows)
                model = FactorModel(written(parts, "factors"), self.rank, dims, history)
                if trace or self.tol:
                    history.append(self.trace_entry(iteration, began, model, tensor, test))
                    if self.tol and last is not None and last - history[-1]["train_rmse"] < self.tol:
                        break
                    last = history[-1]["train_rmse"]
        self._release([placed])
        return model
