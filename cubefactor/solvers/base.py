"""What all solvers share: parameters, the trace, and the clock."""

from __future__ import annotations

import math
import random
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame

from .. import metrics
from ..model import FactorModel
from ..operators.tensor import TensorFrame


@dataclass
class Solver:
    """Parameters common to all methods."""

    rank: int
    outer_iters: int = 10
    reg_param: float = 0.01
    reg: str = "weighted"
    machines: int = 4
    assignment: str = "greedy"
    seed: int = 42
    init: str = "zero_first"
    tol: float = 0.0

    method = "solver"

    def __post_init__(self) -> None:
        if self.rank < 1 or self.outer_iters < 1 or self.machines < 1 or self.reg_param < 0:
            raise ValueError("rank, outer_iters and machines must be at least 1, reg_param at least 0")
        if self.reg not in ("weighted", "plain") or self.init not in ("zero_first", "random"):
            raise ValueError("reg is weighted or plain, init is zero_first or random")

    def trace_entry(self, iteration: int, began: float, model: FactorModel, tensor: TensorFrame, test: DataFrame | None) -> dict:
        """Method, iteration, seconds so far, loss, training and held-out RMSE, held-out cells with a row unseen in
        training, exchanges of updated rows so far, and status."""
        seconds = time.time() - began
        train = metrics.rmse(model, tensor.cells)
        return {
            "method": self.method,
            "iter": iteration,
            "seconds": seconds,
            "loss": metrics.loss(model, tensor, self.reg_param, self.reg).first()["loss"],
            "train_rmse": train,
            "rmse": metrics.rmse(model, test) if test is not None else None,
            "cold": (model.trace[0]["cold"] if model.trace else metrics.cold_cells(tensor, test)) if test is not None else None,
            "exchanges": iteration * self.exchanges(tensor.n_modes),
            "status": "ok" if math.isfinite(train or 0.0) else "diverged",
        }

    def exchanges(self, n_modes: int) -> int:
        """Exchanges of updated rows in one outer iteration: after each update of a mode's rows for a group of columns,
        after each stratum, or once where replicas are averaged."""
        width = getattr(self, "group_width", 0)
        if width:
            return -(-self.rank // width) * self.inner_iters * n_modes
        return self.machines ** (n_modes - 1) if self.method == "stratified_sgd" else 1

    def column_groups(self, width: int, order: str, iteration: int) -> list[list[int]]:
        """Columns cut into groups of `width`, the last one narrower; drawn without replacement if `random`."""
        columns = list(range(self.rank))
        if order == "random":
            random.Random(self.seed * 1009 + iteration).shuffle(columns)
        return [sorted(columns[a : a + width]) for a in range(0, self.rank, width)]
