"""The experiment workloads: convergence, scaling, ablations. Times are measured, so they have no SQL."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from .. import synth
from ..operators.lineage import written
from ..operators.tensor import TensorFrame, split
from ..plans import cost
from ..solvers.sgd import AveragedSGD, StratifiedSGD
from ..solvers.subset_als import ColumnCD, FullALS, SubsetALS
from ..sources.catalog import RECIPES, tensor
from .common import traced, union
from .costs import sizes

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
_PLANTED: dict = {}


def planted_events(spark, sf) -> TensorFrame:
    """Event coordinates with planted rank-3 values; the raw values hold nothing to learn."""
    key = (spark.sparkContext.applicationId, sf)
    if key not in _PLANTED:
        t = synth.planted_on(tensor(spark, sf, "events3"), 3)
        _PLANTED[key] = TensorFrame(written(t.cells, "planted"), t.dims)
    return _PLANTED[key]


def solvers(rank=4, outer=2, lam=0.001, eta=0.05, width=2) -> dict:
    shared = {"outer_iters": outer, "reg_param": lam}
    return {
        "column_cd": ColumnCD(rank, storage="single", **shared),
        "subset_als": SubsetALS(rank, group_width=min(width, rank), storage="single", **shared),
        "full_als": FullALS(rank, storage="single", **shared),
        "averaged_sgd": AveragedSGD(rank, eta0=eta, machines=4, **shared),
        "stratified_sgd": StratifiedSGD(rank, eta0=eta, machines=2, **shared),
    }


def timed(solver, t: TensorFrame) -> tuple[float | None, str]:
    """Seconds of a run and its status: a run that is refused has no seconds."""
    began = time.time()
    try:
        solver.fit(t)
    except MemoryError:
        return None, "oom"
    except RuntimeError as refused:
        if not str(refused).startswith("oot"):
            raise
        return None, "oot"
    return time.time() - began, "ok"


def _converge(method, source, **options):
    def run(spark, sf):
        train, test = split(source(spark, sf))
        return traced(solvers(**options)[method].fit(train, test, trace=True).trace, spark)

    return run


for _method in cost.METHODS:
    QUERIES[f"converge_{_method}"] = _converge(_method, planted_events)
    QUERIES[f"converge_tokens3_{_method}"] = _converge(_method, lambda spark, sf: tensor(spark, sf, "tokens3"), rank=3, lam=0.01, eta=0.01)


def inner_iters_sweep(spark, sf):
    """The single-column method's held-out error with 1, 2 and 5 sweeps over the modes for each column."""
    train, test = split(planted_events(spark, sf))
    runs = [(n, ColumnCD(2, outer_iters=2, inner_iters=n, reg_param=0.001, storage="single")) for n in (1, 2, 5)]
    return union([traced(solver.fit(train, test, trace=True).trace, spark, inner_iters=n) for n, solver in runs])


def group_width_sweep(spark, sf):
    """Held-out error, seconds of an iteration and bytes held, by the number of columns solved together."""
    train, test = split(planted_events(spark, sf))
    rank = 20
    runs = [(c, SubsetALS(rank, group_width=c, outer_iters=1, reg_param=0.001, storage="single")) for c in (4, 10, rank)]
    return union([traced(solver.fit(train, test, trace=True).trace, spark, group_width=c, memory_bytes=cost.memory("subset_als", train.dims, rank, c)) for c, solver in runs])


QUERIES["inner_iters_sweep"] = inner_iters_sweep
QUERIES["group_width_sweep"] = group_width_sweep
#: Place of each grid factor among the published scales' numbers.
_FACTORS = {"modes": 0, "length": 1, "cells": 2, "rank": 3}
SCALED = "method string, factor string, value long, seconds double, operations double, status string"


def published_status(method: str, factor: str, step: int) -> str:
    """Outcome of a method at the published size: one factor at the given step, the others at the second."""
    scales = list(cost.SCALES.values())
    size = list(scales[1])
    size[_FACTORS[factor]] = scales[step][_FACTORS[factor]]
    n, length, nnz, k = size
    return cost.feasible(method, [length] * n, k, 10, cost.machines_of(method), nnz=nnz)


def _scaled(spark, sf, **factor):
    """Seconds of one iteration of each method with one factor varied (a scaled-down grid).

    What would not fit the published cluster at the step's published size is marked and not run.
    """
    base = {"modes": 3, "length": 300, "cells": 3000, "rank": 2}
    (name, values), parts = next(iter(factor.items())), []
    for step, value in enumerate(values):
        size = base | {name: value}
        t = synth.planted(spark, [size["length"]] * size["modes"], size["cells"], 3)
        t = TensorFrame(written(t.cells, "scaled"), t.dims)
        for method, solver in solvers(size["rank"], 1, width=10).items():
            seconds, status = None, published_status(method, name, step)
            if status == "ok":
                seconds, status = timed(solver, t)
            parts.append((method, name, value, seconds, float(cost.flops(method, size["cells"], t.dims, size["rank"], min(10, size["rank"]), 1)), status))
    return spark.createDataFrame(parts, SCALED)


QUERIES["scale_dimension"] = lambda spark, sf: _scaled(spark, sf, modes=synth.GRID["modes"])
QUERIES["scale_observations"] = lambda spark, sf: _scaled(spark, sf, cells=synth.GRID["cells"])
QUERIES["scale_length"] = lambda spark, sf: _scaled(spark, sf, length=synth.GRID["length"])
QUERIES["scale_rank"] = lambda spark, sf: _scaled(spark, sf, rank=synth.GRID["rank"][:2])


def scale_overall(spark, sf):
    """All factors grow together over four steps; methods that would not fit or end at the published size are marked."""
    parts = []
    for step, (n, length, cells, rank) in enumerate(((2, 300, 3000, 2), (3, 1000, 10_000, 3), (4, 3000, 30_000, 4), (5, 10_000, 100_000, 5))):
        t = synth.planted(spark, [length] * n, cells, 3)
        t = TensorFrame(written(t.cells, "scaled"), t.dims)
        modes, rows, nnz, k = list(cost.SCALES.values())[step]
        for method, solver in solvers(rank, 1, width=10).items():
            seconds, status = None, cost.feasible(method, [rows] * modes, k, 10, cost.machines_of(method), nnz=nnz)
            if status == "ok":
                seconds, status = timed(solver, t)
            parts.append((method, f"S{step + 1}", cost.machines_of(method), seconds, status))
        parts.append(("stratified_sgd", f"S{step + 1}", 40, None, cost.feasible("stratified_sgd", [rows] * modes, k, 10, 40, nnz=nnz)))
    return spark.createDataFrame(parts, "method string, scale string, machines int, seconds double, status string")


def machine_speedup(spark, sf):
    """Seconds of each method by number of machines, against the first number."""
    t, parts = planted_events(spark, sf), []
    for method in cost.METHODS:
        first = None
        for m in (1, 2, 4):
            options = {"outer_iters": 1, "reg_param": 0.001, "machines": m}
            solver = {
                "column_cd": lambda o: ColumnCD(1, **o),
                "subset_als": lambda o: SubsetALS(2, group_width=2, **o),
                "full_als": lambda o: FullALS(2, **o),
                "averaged_sgd": lambda o: AveragedSGD(2, **o),
                "stratified_sgd": lambda o: StratifiedSGD(2, **o),
            }[method](options)
            seconds, _ = timed(solver, t)
            first = first or seconds
            parts.append((method, m, seconds, first / seconds))
    return spark.createDataFrame(parts, "method string, machines int, seconds double, speedup double")


#: Cells of the optimization grid: where the cells are, and who owns the rows.
CELLS = [(storage, how) for storage in ("none", "mode_copies") for how in ("sequential", "random", "greedy")]


def _grid(spark, sf, methods: dict) -> list[tuple]:
    """Seconds of each method in each cell, and the speed-up over no copies with sequential rows."""
    t, parts = planted_events(spark, sf), []
    for method, (make, cells, width) in methods.items():
        first = None
        for storage, how in cells:
            seconds, _ = timed(make(storage, how), t)
            first = first or seconds
            parts.append((method, storage, how, seconds, first / seconds, cost.redistributions(1, 2, width, 3, 1, storage)))
    return parts


ABLATION = "method string, storage string, assignment string, seconds double, speedup double, redistributions int"


def optimization_ablation(spark, sf):
    """The single-column method with and without mode copies, by row assignment: all six cells."""
    make = lambda storage, how: ColumnCD(2, outer_iters=1, storage=storage, assignment=how)
    return spark.createDataFrame(_grid(spark, sf, {"column_cd": (make, CELLS, 1)}), ABLATION)


def optimization_grid(spark, sf):
    """The same for the other methods; strata keep their cells in place, so only the row assignment varies there.

    Averaged replicas own no rows: the assignment does not apply.
    """
    methods = {
        "subset_als": (lambda storage, how: SubsetALS(2, group_width=2, outer_iters=1, storage=storage, assignment=how), CELLS, 2),
        "full_als": (lambda storage, how: FullALS(2, outer_iters=1, storage=storage, assignment=how), CELLS, 2),
        "stratified_sgd": (lambda storage, how: StratifiedSGD(2, outer_iters=1, machines=2, assignment=how), CELLS[3:], 2),
    }
    rows = _grid(spark, sf, methods) + [("averaged_sgd", None, None, None, None, None)]
    return spark.createDataFrame(rows, ABLATION)


QUERIES |= {"scale_overall": scale_overall, "machine_speedup": machine_speedup, "optimization_ablation": optimization_ablation, "optimization_grid": optimization_grid}
QUERIES["averaged_sgd_run"] = lambda spark, sf: solvers()["averaged_sgd"].fit(planted_events(spark, sf)).factors
QUERIES["stratified_sgd_run"] = lambda spark, sf: solvers()["stratified_sgd"].fit(planted_events(spark, sf)).factors


def scaling_status(spark, sf):
    """Outcome of every method if the supply tensor grew as the published grid does: fits, out of memory, out of time.

    Lengths and cells are the tensor's, counted in its table, times the published steps' shares of the second step.
    """
    dims, nnz, _ = sizes(spark, sf, ["supply3"])["supply3"]
    steps = list(cost.SCALES.values())
    _, length, cells, _ = steps[1]
    rows = []
    for factor, at in _FACTORS.items():
        for step, scale in enumerate(steps):
            size = list(steps[1])
            size[at] = scale[at]
            n, i, z, k = size
            for method in cost.METHODS:
                rows.append((method, factor, step + 1, cost.feasible(method, [max(dims) * i // length] * n, k, 10, cost.machines_of(method), nnz=nnz * z // cells)))
    return spark.createDataFrame(rows, "method string, factor string, step int, status string")


QUERIES["scaling_status"] = scaling_status
#: In this grid only memory ends runs: all parameters of a mode-long row set in 8 GiB, a fifth of them with strata.
ORACLE_SQL["scaling_status"] = (
    f"WITH own AS MATERIALIZED (SELECT greatest(count(DISTINCT k1), count(DISTINCT k2), count(DISTINCT k3)) AS longest FROM ({RECIPES['supply3'].sql}) WHERE k1 IS NOT NULL AND k2 IS NOT NULL AND k3 IS NOT NULL AND x IS NOT NULL), "
    "scales AS (SELECT step, n, longest * i // 1000000 AS i, k FROM own, (VALUES " + ", ".join(f"({s}, {n}, {i}, {k})" for s, (n, i, z, k) in enumerate(cost.SCALES.values(), 1)) + ") v(step, n, i, k)), "
    "base AS (SELECT * FROM scales WHERE step = 2), grid AS ("
    "SELECT 'modes' AS factor, s.step, s.n, b.i, b.k FROM scales s, base b UNION ALL SELECT 'length', s.step, b.n, s.i, b.k FROM scales s, base b "
    "UNION ALL SELECT 'cells', s.step, b.n, b.i, b.k FROM scales s, base b UNION ALL SELECT 'rank', s.step, b.n, b.i, s.k FROM scales s, base b), "
    "methods(method) AS (VALUES ('column_cd'), ('subset_als'), ('full_als'), ('averaged_sgd'), ('stratified_sgd')) "
    "SELECT method, factor, CAST(step AS INT) AS step, CASE WHEN method IN ('full_als', 'averaged_sgd') AND CAST(n AS BIGINT) * i * k * 4 > 8589934592 "
    "OR method = 'stratified_sgd' AND CAST(n AS BIGINT) * i * k * 4 / 5 > 8589934592 THEN 'oom' ELSE 'ok' END AS status FROM grid, methods"
)


def model_use(spark, sf):
    """The three best hours for each user and event type, without hours already seen."""
    t = planted_events(spark, sf)
    model = solvers(3, 1)["full_als"].fit(t)
    users = t.cells.select("i1").distinct().crossJoin(t.cells.select("i2").distinct())  # the question: every user and each of the few types
    return model.recommend(users, 3, 3, {}, t.cells).select("i1", "i2", "i3", "rank", F.round("prediction", 4).alias("prediction"))


QUERIES["recommend_hours"] = model_use
