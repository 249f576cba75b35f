"""Whole runs of the least-squares solvers, compared with a chain of SQL steps."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans.sqlgen import Chain
from ..solvers.subset_als import ColumnCD, FullALS, SubsetALS
from ..sources.catalog import cells_sql, tensor
from .common import long_factors, rounded

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
FAST = {"storage": "single", "machines": 4}


def _factors(name, solver, width, outer, inner=1, digits=5, lam=0.05, reg="weighted"):
    rank = solver["rank"]

    def run(spark, sf):
        kind = {"cd": ColumnCD, "subset": SubsetALS, "full": FullALS}[solver["kind"]]
        options = {k: v for k, v in solver.items() if k != "kind"}
        if solver["kind"] == "subset":
            options |= {"group_width": width, "column_order": "fixed"}
        return long_factors(kind(outer_iters=outer, inner_iters=inner, reg_param=lam, reg=reg, **options).fit(tensor(spark, sf, name)), digits)

    chain = Chain(cells_sql(name), 3, rank, lam=lam, reg=reg)
    for _ in range(outer):
        chain.outer(width, inner)
    return run, chain.sql(chain.factors(digits))


for _query, _args in {
    "cd_one_column": ("events3", {"kind": "cd", "rank": 1, "machines": 4}, 1, 1),
    "cd_two_columns": ("events3", {"kind": "cd", "rank": 2, "machines": 4}, 1, 1),
    "cd_rank3_iter3": ("events3", {"kind": "cd", "rank": 3, **FAST}, 1, 3),
    "cd_rank2_iter2": ("purchases3", {"kind": "cd", "rank": 2, **FAST}, 1, 2),
    "cd_inner2": ("events3", {"kind": "cd", "rank": 2, **FAST}, 1, 1, 2),
    "cd_plain": ("events3", {"kind": "cd", "rank": 1, "storage": "none", "machines": 4}, 1, 1, 1, 5, 0.5, "plain"),
    "subset_c2_iter2": ("events3", {"kind": "subset", "rank": 4, **FAST}, 2, 2),
    "subset_last_group_narrow": ("events3", {"kind": "subset", "rank": 3, **FAST}, 2, 1),
    "full_als_k2_iter2": ("events3", {"kind": "full", "rank": 2, **FAST}, 2, 2),
    "full_als_k3_supply": ("supply3", {"kind": "full", "rank": 3, **FAST}, 3, 1, 1, 3),
}.items():
    QUERIES[_query], ORACLE_SQL[_query] = _factors(*_args)


def subset_equals_full(spark, sf):
    """Rows where one group of all columns differs from full least squares: none."""
    t = tensor(spark, sf, "events3")
    one = long_factors(SubsetALS(2, group_width=2, outer_iters=1, reg_param=0.05, column_order="fixed", **FAST).fit(t), 7)
    two = long_factors(FullALS(2, outer_iters=1, reg_param=0.05, **FAST).fit(t), 7)
    return one.exceptAll(two).agg(F.count("*").alias("different"))


QUERIES["subset_equals_full"] = subset_equals_full
ORACLE_SQL["subset_equals_full"] = "SELECT CAST(0 AS BIGINT) AS different"


def fused_vs_unfused(spark, sf):
    """Rows where the fused residual changes single-column results: none."""
    t = tensor(spark, sf, "events3")
    one = long_factors(ColumnCD(2, outer_iters=1, reg_param=0.05, **FAST).fit(t), 7)
    two = long_factors(ColumnCD(2, outer_iters=1, reg_param=0.05, fused=False, **FAST).fit(t), 7)
    return one.exceptAll(two).agg(F.count("*").alias("different"))


QUERIES["fused_vs_unfused"] = fused_vs_unfused
ORACLE_SQL["fused_vs_unfused"] = "SELECT CAST(0 AS BIGINT) AS different"


def flagship(spark, sf):
    """Two columns by coordinate descent on the event tensor: predictions beside the values."""
    t = tensor(spark, sf, "events3")
    model = ColumnCD(2, outer_iters=2, reg_param=0.05, **FAST).fit(t)
    return model.predict(t.cells).select("i1", "i2", "i3", rounded("x", 5).alias("x"), rounded("prediction", 4).alias("prediction"))


QUERIES["flagship"] = flagship
_chain = Chain(cells_sql("events3"), 3, 2, lam=0.05)
_chain.outer(1)
_chain.outer(1)
_from, _names = _chain._joined("cells", [0, 1], [1, 2, 3])
ORACLE_SQL["flagship"] = _chain.sql(f"SELECT c.i1, c.i2, c.i3, round(c.x, 5) + 0.0 AS x, round({_chain._total([0, 1], _names)}, 4) + 0.0 AS prediction FROM {_from}")
