"""Single steps on portable factors: sums, solves, residuals, losses, one gradient step."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import metrics
from ..functions.init import hash_factors, start_slice
from ..functions.kernels import add_back_group, attach, normal_equations, predict_expr, solve_rows, subtract_group
from ..functions.schedule import inverse_time
from ..model import FactorModel
from ..operators.layout import with_blocks
from ..operators.tensor import held_out, held_out_sql, portable_sql
from ..plans.sqlgen import Chain
from ..solvers.sgd import average_replicas
from ..sources.catalog import cells_sql, tensor
from .common import rounded, union

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
NAMES = ["a1", "a2", "a3"]


def _slices(t, width, seed=42):
    spark = t.cells.sparkSession
    return [start_slice(spark, d, n, list(range(width)), seed, "random") for n, d in enumerate(t.dims, 1)]


def _equations(name, width):
    def run(spark, sf):
        t = tensor(spark, sf, name)
        sums = normal_equations(attach(t.cells, _slices(t, width), "a", modes=[2, 3]), 1, width, NAMES, F.col("x"), ["i1"])
        keep = [c for c in sums.columns if c[0] in "gb"]
        return sums.select(F.col("i1").alias("idx"), *(rounded(c, 4).alias(c.replace("_", "")) for c in keep), F.col("n").cast("long").alias("n"))

    chain = Chain(cells_sql(name), 3, width, lam=0.0, init="random")
    table = chain.equations("r0", 1, list(range(width)))
    columns = [f"g{a}{b}" for a in range(width) for b in range(a, width)] + [f"b{a}" for a in range(width)]
    return run, chain.sql(f"SELECT idx, {', '.join(f'round({c}, 4) + 0.0 AS {c}' for c in columns)}, CAST(n AS BIGINT) AS n FROM {table}")


QUERIES["normal_eq_c1"], ORACLE_SQL["normal_eq_c1"] = _equations("events3", 1)
QUERIES["normal_eq_c2"], ORACLE_SQL["normal_eq_c2"] = _equations("purchases3", 2)


def _solved(name, width, mode, lam=0.1, reg="weighted"):
    def run(spark, sf):
        t = tensor(spark, sf, name)
        others = [n for n in (1, 2, 3) if n != mode]
        sums = normal_equations(attach(t.cells, _slices(t, width), "a", modes=others), mode, width, NAMES, F.col("x"), [f"i{mode}"])
        return solve_rows(sums, width, lam, reg, f"i{mode}").select("idx", F.posexplode("a").alias("component", "value")).select("idx", "component", rounded("value", 5).alias("value"))

    chain = Chain(cells_sql(name), 3, width, lam=lam, reg=reg, init="random")
    chain.solve("r0", mode, list(range(width)))
    return run, chain.sql(" UNION ALL ".join(f"SELECT idx, {k} AS component, round({chain.value[mode, k][1]}, 5) + 0.0 AS value FROM {chain.value[mode, k][0]}" for k in range(width)))


QUERIES["subset_c2_step"], ORACLE_SQL["subset_c2_step"] = _solved("purchases3", 2, 3)
QUERIES["full_als_k2_step"], ORACLE_SQL["full_als_k2_step"] = _solved("events3", 2, 1)
QUERIES["full_als_k3_step"], ORACLE_SQL["full_als_k3_step"] = _solved("events3", 3, 1)
QUERIES["plain_reg_step"], ORACLE_SQL["plain_reg_step"] = _solved("events3", 2, 2, 0.5, "plain")


def residual_update(spark, sf):
    """Residual with one group added back and another version of it subtracted."""
    t = tensor(spark, sf, "events3")
    joined = attach(attach(t.cells.withColumn("r", F.col("x")), _slices(t, 2), "a"), _slices(t, 2, 7), "b")
    changed = joined.withColumn("rhat", add_back_group(2, 3, "r", "a")).withColumn("r2", subtract_group(2, 3, "rhat", "b"))
    return changed.select("i1", "i2", "i3", rounded("rhat").alias("rhat"), rounded("r2").alias("r2"))


def _products(seed, width, n_modes=3):
    return " + ".join("(" + " * ".join(f"({portable_sql(f'i{n}', n, k, seed)})" for n in range(1, n_modes + 1)) + ")" for k in range(width))


QUERIES["residual_update"] = residual_update
ORACLE_SQL["residual_update"] = f"SELECT i1, i2, i3, round(x + {_products(42, 2)}, 6) + 0.0 AS rhat, round(x + {_products(42, 2)} - ({_products(7, 2)}), 6) + 0.0 AS r2 FROM ({cells_sql('events3')})"


def _model(t, rank):
    return FactorModel(hash_factors(t.cells.sparkSession, t.dims, rank), rank, t.dims)


def _loss(reg):
    def run(spark, sf):
        t = tensor(spark, sf, "purchases3")
        return metrics.loss(_model(t, 2), t, 0.1, reg).select(*(rounded(c, 2).alias(c) for c in ("error", "penalty", "loss")))

    rows = " UNION ALL ".join(f"SELECT i{n} AS idx, {n} AS mode, count(*) AS n, {' + '.join(f'power({portable_sql(f'i{n}', n, k)}, 2)' for k in range(2))} AS q FROM cells GROUP BY i{n}" for n in (1, 2, 3))
    weight = "q * n" if reg == "weighted" else "q"
    return run, f"WITH cells AS MATERIALIZED ({cells_sql('purchases3')}), e AS (SELECT sum(power(x - ({_products(42, 2)}), 2)) AS error FROM cells), p AS (SELECT sum({weight}) * CAST(0.1 AS DOUBLE) AS penalty FROM ({rows})) SELECT round(error, 2) + 0.0 AS error, round(penalty, 2) + 0.0 AS penalty, round(error + penalty, 2) + 0.0 AS loss FROM e, p"


QUERIES["loss_plain"], ORACLE_SQL["loss_plain"] = _loss("plain")
QUERIES["loss_weighted"], ORACLE_SQL["loss_weighted"] = _loss("weighted")


def rmse_holdout(spark, sf):
    t = tensor(spark, sf, "purchases3")
    return metrics.report(_model(t, 2), t.cells.where(held_out(t))).select("cells", *(rounded(c).alias(c) for c in ("rmse", "mae", "r2", "nmse")))


QUERIES["rmse_holdout"] = rmse_holdout
ORACLE_SQL["rmse_holdout"] = f"WITH e AS (SELECT x, x - ({_products(42, 2)}) AS e FROM ({cells_sql('purchases3')}) WHERE {held_out_sql(['i1', 'i2', 'i3'])}) SELECT count(*) AS cells, round(sqrt(avg(e * e)), 6) + 0.0 AS rmse, round(avg(abs(e)), 6) + 0.0 AS mae, round(1 - sum(e * e) / (var_pop(x) * count(*)), 6) + 0.0 AS r2, round(sum(e * e) / sum(x * x), 6) + 0.0 AS nmse FROM e"


def predict_cells(spark, sf):
    t = tensor(spark, sf, "events3")
    return _model(t, 3).predict(t.cells, 0.0, 0.75).select("i1", "i2", "i3", rounded("prediction").alias("prediction"))


QUERIES["predict_cells"] = predict_cells
ORACLE_SQL["predict_cells"] = f"SELECT i1, i2, i3, round(least(greatest({_products(42, 3)}, 0.0), 0.75), 6) + 0.0 AS prediction FROM ({cells_sql('events3')})"


def average_of_replicas(spark, sf):
    """The averaging of three replicas with fixed parameters."""
    t = tensor(spark, sf, "events3")
    return average_replicas(union([hash_factors(spark, t.dims, 2, seed) for seed in (1, 2, 3)]), 2).select("mode", "idx", rounded(F.get("f", F.lit(0))).alias("f0"), rounded(F.get("f", F.lit(1))).alias("f1"))


QUERIES["average_replicas"] = average_of_replicas
ORACLE_SQL["average_replicas"] = f"WITH cells AS MATERIALIZED ({cells_sql('events3')}) " + " UNION ALL ".join(
    f"SELECT {n} AS mode, idx, " + ", ".join("round((" + " + ".join(f"({portable_sql('idx', n, k, s)})" for s in (1, 2, 3)) + f") / 3.0, 6) + 0.0 AS f{k}" for k in (0, 1)) + f" FROM (SELECT DISTINCT i{n} AS idx FROM cells)" for n in (1, 2, 3)
)


def sgd_single_cell_per_block(spark, sf):
    """One gradient step on the first cell of each block of a stratum: no two share a row, so order is free."""
    t = tensor(spark, sf, "events3")
    first = with_blocks(t, 2).where("stratum = 0").groupBy("b1").agg(F.min(F.struct("i1", "i2", "i3", "x")).alias("c")).select("c.*")
    joined = attach(first, _slices(t, 2), "a")
    error = F.col("x") - predict_expr(NAMES, 2)
    eta, lam = inverse_time(0.05, 1), 0.1
    rows = []
    for n in (1, 2, 3):
        for k in (0, 1):
            own = F.get(f"a{n}", F.lit(k))
            other = F.lit(1.0)
            for m in (1, 2, 3):
                other = other * F.get(f"a{m}", F.lit(k)) if m != n else other
            rows.append(F.struct(F.lit(n).alias("mode"), F.col(f"i{n}").alias("idx"), F.lit(k).alias("component"), (own + 2 * eta * (error * other - lam * own)).alias("value")))
    return joined.select(F.explode(F.array(*rows)).alias("s")).select("s.mode", "s.idx", "s.component", rounded("s.value").alias("value"))


QUERIES["sgd_single_cell_per_block"] = sgd_single_cell_per_block
_BLOCK = [f"CASE WHEN (i{n} + 1) * 2 <= (SELECT max(i{n}) + 1 FROM cells) THEN 0 ELSE 1 END" for n in (1, 2, 3)]
_V = {(n, k): f"({portable_sql(f'i{n}', n, k)})" for n in (1, 2, 3) for k in (0, 1)}
ORACLE_SQL["sgd_single_cell_per_block"] = (
    f"WITH cells AS MATERIALIZED ({cells_sql('events3')}), b AS (SELECT *, {_BLOCK[0]} AS b1, {_BLOCK[1]} AS b2, {_BLOCK[2]} AS b3 FROM cells), f AS (SELECT i1, i2, i3, x, x - ({_products(42, 2)}) AS e FROM b WHERE b1 = b2 AND b2 = b3 QUALIFY row_number() OVER (PARTITION BY b1 ORDER BY i1, i2, i3) = 1) "
    + " UNION ALL ".join(f"SELECT {n} AS mode, i{n} AS idx, {k} AS component, round({_V[n, k]} + 2 * {inverse_time(0.05, 1)} * (e * {' * '.join(_V[m, k] for m in (1, 2, 3) if m != n)} - 0.1 * {_V[n, k]}), 6) + 0.0 AS value FROM f" for n in (1, 2, 3) for k in (0, 1))
)
