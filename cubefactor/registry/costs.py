"""Cost tables of the five methods for tensors of the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans import cost
from ..sources.catalog import RECIPES

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
#: Tensors whose sizes are taken from the tables, and the rank that each is to be factorized at.
RANKS = {"events3": 30, "supply3": 100, "events4": 300}


def sizes(spark, sf, names=tuple(RANKS)) -> dict[str, tuple[list[int], int, int]]:
    """Mode lengths, cells and rank of tensors, counted in the tables anew: one row of counts per tensor."""
    out = {}
    for name in names:
        recipe = RECIPES[name]
        raw, keys = recipe.build(spark, sf), [f"k{n}" for n in range(1, recipe.n_modes + 1)]
        nnz, *dims = raw.agg(F.count("*"), *(F.countDistinct(k) for k in keys)).first()
        out[name] = (dims, nnz, RANKS[name])
    return out


def _size_sql(name: str) -> str:
    keys = [f"k{n}" for n in range(1, RECIPES[name].n_modes + 1)]
    rest = " + ".join(f"count(DISTINCT {k})" for k in keys[1:])
    here = " AND ".join(f"{k} IS NOT NULL" for k in [*keys, "x"])
    return f"SELECT '{name}' AS scale, CAST({len(keys)} AS BIGINT) AS n, CAST({rest} AS BIGINT) AS rest, CAST(count(DISTINCT k1) + {rest} AS BIGINT) AS rows, count(*) AS nnz, CAST({RANKS[name]} AS BIGINT) AS k FROM ({RECIPES[name].sql}) WHERE {here}"


_BASE = f"WITH scales AS MATERIALIZED ({' UNION ALL '.join(map(_size_sql, RANKS))}), methods(method, m) AS (VALUES " + ", ".join(f"('{x}', {cost.machines_of(x)})" for x in cost.METHODS) + "), g AS (SELECT * FROM scales, methods)"

QUERIES["cost_table"] = lambda spark, sf: cost.table(spark, sizes(spark, sf)).select("scale", "method", F.col("flops").cast("long").alias("operations"), "convergence")
ORACLE_SQL["cost_table"] = f"""{_BASE} SELECT scale, method, CAST(CASE method
 WHEN 'column_cd' THEN nnz * n * k * (n + 1) // m + k * rows // m
 WHEN 'subset_als' THEN nnz * n * k * (n + 10) // m + k * 100 * rows // m
 WHEN 'full_als' THEN nnz * n * k * (n + k) // m + k * k * k * rows // m
 ELSE nnz * n * k // m END AS BIGINT) AS operations,
 CASE WHEN method IN ('subset_als', 'full_als') THEN 'fastest' WHEN method = 'averaged_sgd' THEN 'slow' ELSE 'fast' END AS convergence FROM g"""
QUERIES["exchange_table"] = lambda spark, sf: cost.table(spark, sizes(spark, sf)).select("scale", "method", F.col("exchanged").cast("long").alias("parameters"))
ORACLE_SQL["exchange_table"] = f"{_BASE} SELECT scale, method, CAST(CASE method WHEN 'stratified_sgd' THEN CAST(power(m, n - 1) AS BIGINT) * k * rest // m ELSE k * rows END AS BIGINT) AS parameters FROM g"
QUERIES["memory_table"] = lambda spark, sf: cost.table(spark, sizes(spark, sf)).select("scale", "method", "memory_bytes", "status")
_HELD = "4 * CASE method WHEN 'column_cd' THEN 2 * rows WHEN 'subset_als' THEN least(10, k) * rows WHEN 'stratified_sgd' THEN k * rows // m ELSE k * rows END"
ORACLE_SQL["memory_table"] = f"{_BASE} SELECT scale, method, CAST({_HELD} AS BIGINT) AS memory_bytes, CASE WHEN {_HELD} <= CAST(8589934592 AS BIGINT) THEN 'ok' ELSE 'oom' END AS status FROM g"


def redistribution_table(spark, sf):
    """Passes that move all cells for ten outer iterations of forty columns over three modes, and the cells of the
    event tensor that they move."""
    _, cells, _ = sizes(spark, sf, ["events3"])["events3"]
    passes = [(s, c, ti, cost.redistributions(10, 40, c, 3, ti, s)) for s in ("none", "single", "mode_copies") for c in (1, 10, 40) for ti in (1, 5)]
    return spark.createDataFrame([(*row, row[-1] * cells) for row in passes], "storage string, group_width long, inner_iters long, redistributions long, cells_moved long")


QUERIES["redistribution_table"] = redistribution_table
_PASSES = "SELECT s AS storage, CAST(c AS BIGINT) AS group_width, CAST(ti AS BIGINT) AS inner_iters, CAST(CASE s WHEN 'none' THEN 10 * (40 // c) * (ti * 3 + 2) WHEN 'single' THEN 1 ELSE 3 END AS BIGINT) AS redistributions FROM (VALUES ('none'), ('single'), ('mode_copies')) a(s), (VALUES (1), (10), (40)) b(c), (VALUES (1), (5)) d(ti)"
ORACLE_SQL["redistribution_table"] = f"SELECT p.*, CAST(redistributions * nnz AS BIGINT) AS cells_moved FROM ({_PASSES}) p, ({_size_sql('events3')}) e"
QUERIES["scalability_table"] = lambda spark, sf: cost.scalability(spark, *sizes(spark, sf, ["supply3"])["supply3"][:2])
_FITS = lambda times, k: f"4 * CASE method WHEN 'column_cd' THEN 2 * {times} * longest WHEN 'subset_als' THEN 10 * {times} * longest WHEN 'stratified_sgd' THEN {times} * longest * {k} // 5 ELSE {times} * longest * {k} END <= CAST(8589934592 AS BIGINT)"
ORACLE_SQL["scalability_table"] = (
    f"SELECT method, method <> 'stratified_sgd' AS dimension, {_FITS(3, 100)} AS observations, {_FITS(30, 100)} AS length, method <> 'full_als' AND {_FITS(3, 1000)} AS rank, method NOT IN ('averaged_sgd', 'stratified_sgd') AS machines "
    f"FROM (SELECT greatest(count(DISTINCT k1), count(DISTINCT k2), count(DISTINCT k3)) AS longest FROM ({RECIPES['supply3'].sql}) WHERE k1 IS NOT NULL AND k2 IS NOT NULL AND k3 IS NOT NULL AND x IS NOT NULL), (VALUES " + ", ".join(f"('{x}')" for x in cost.METHODS) + ") t(method)"
)
