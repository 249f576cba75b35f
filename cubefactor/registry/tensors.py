"""Tensors from the tables: cells, counts, profiles, splits, assignments, layouts."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import layout
from ..operators.tensor import fix_mode, held_out, held_out_sql, marginalize, mode_counts, portable_sql, unfold, validate
from ..sources.catalog import RECIPES, cells_sql, tensor
from .common import rounded, union

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
PROFILED = ("purchases3", "supply3", "events3", "events4", "tokens3", "embed2", "labelled3")
MACHINES = 8


def _cells(name):
    def run(spark, sf):
        t = tensor(spark, sf, name)
        return t.cells.select(*t.modes, rounded("x").alias("x"))

    modes = ", ".join(f"i{n}" for n in range(1, RECIPES[name].n_modes + 1))
    return run, f"SELECT {modes}, round(x, 6) + 0.0 AS x FROM ({cells_sql(name)})"


for _name in RECIPES:
    _query = "bin30_events" if _name == "events_bin30" else f"tensor_{_name}"
    QUERIES[_query], ORACLE_SQL[_query] = _cells(_name)


def counts_sql(name: str) -> str:
    parts = [f"SELECT {n} AS mode, i{n} AS idx, count(*) AS nnz FROM cells GROUP BY i{n}" for n in range(1, RECIPES[name].n_modes + 1)]
    return f"WITH cells AS MATERIALIZED ({cells_sql(name)}) " + " UNION ALL ".join(parts)


for _name in ("events3", "purchases3", "supply3", "tokens3", "geo5"):
    QUERIES[f"mode_counts_{_name}"] = lambda spark, sf, n=_name: mode_counts(tensor(spark, sf, n))
    ORACLE_SQL[f"mode_counts_{_name}"] = counts_sql(_name)


def tensor_profile(spark, sf):
    """Modes, lengths, cells and density of each tensor."""
    parts = []
    for name in PROFILED:
        t = tensor(spark, sf, name)
        space = 1.0
        for d in t.dims:
            space *= d
        per = F.explode(F.array(*(F.struct(F.lit(n).alias("mode"), F.lit(d).cast("long").alias("length")) for n, d in enumerate(t.dims, 1))))
        parts.append(t.cells.agg(F.count("*").alias("nnz")).select(F.lit(name).alias("tensor"), per.alias("m"), "nnz", rounded(F.col("nnz") / F.lit(space), 9).alias("density")).select("tensor", "m.mode", "m.length", "nnz", "density"))
    return union(parts)


def _profile_sql(name):
    n = RECIPES[name].n_modes
    space = " * ".join(f"CAST(count(DISTINCT i{m}) AS DOUBLE)" for m in range(1, n + 1))
    return " UNION ALL ".join(f"SELECT '{name}' AS tensor, {m} AS mode, count(DISTINCT i{m}) AS length, count(*) AS nnz, round(count(*) / ({space}), 9) + 0.0 AS density FROM ({cells_sql(name)})" for m in range(1, n + 1))


QUERIES["tensor_profile"] = tensor_profile
ORACLE_SQL["tensor_profile"] = " UNION ALL ".join(map(_profile_sql, PROFILED))


def holdout_split(spark, sf):
    """Sizes of the deterministic training and held-out parts."""
    parts = []
    for name in ("purchases3", "tokens3"):
        t = tensor(spark, sf, name)
        parts.append(t.cells.groupBy(held_out(t).alias("held_out")).agg(F.count("*").alias("cells")).select(F.lit(name).alias("tensor"), "held_out", "cells"))
    return union(parts)


QUERIES["holdout_split"] = holdout_split
ORACLE_SQL["holdout_split"] = " UNION ALL ".join(f"SELECT '{n}' AS tensor, {held_out_sql(['i1', 'i2', 'i3'])} AS held_out, count(*) AS cells FROM ({cells_sql(n)}) GROUP BY 2" for n in ("purchases3", "tokens3"))

QUERIES["validate_cells"] = lambda spark, sf: validate(tensor(spark, sf, "events4").cells, tensor(spark, sf, "events4").dims)
ORACLE_SQL["validate_cells"] = f"SELECT count(*) AS cells, CAST(0 AS BIGINT) AS nulls, CAST(0 AS BIGINT) AS nans, CAST(0 AS BIGINT) AS out_of_bounds, CAST(count(*) - count(DISTINCT (i1, i2, i3, i4)) AS BIGINT) AS repeated FROM ({cells_sql('events4')})"

QUERIES["tensor_slice"] = lambda spark, sf: fix_mode(tensor(spark, sf, "events3"), 2, 1).cells.select("i1", "i2", rounded("x").alias("x"))
ORACLE_SQL["tensor_slice"] = f"SELECT i1, i3 AS i2, round(x, 6) + 0.0 AS x FROM ({cells_sql('events3')}) WHERE i2 = 1"
QUERIES["tensor_marginal"] = lambda spark, sf: marginalize(tensor(spark, sf, "supply3"), [1, 3]).cells.select("i1", "i2", rounded("x", 3).alias("x"))
ORACLE_SQL["tensor_marginal"] = f"SELECT i1, i3 AS i2, round(sum(x), 3) + 0.0 AS x FROM ({cells_sql('supply3')}) GROUP BY 1, 2"
QUERIES["tensor_unfold"] = lambda spark, sf: unfold(tensor(spark, sf, "events3"), 2).cells.select("i1", "i2", rounded("x").alias("x"))
ORACLE_SQL["tensor_unfold"] = f"WITH cells AS MATERIALIZED ({cells_sql('events3')}) SELECT i2 AS i1, i1 + i3 * (SELECT max(i1) + 1 FROM cells) AS i2, round(x, 6) + 0.0 AS x FROM cells"


# -- assignments -------------------------------------------------------------------------------------


def _assigned(name, how, machines=MACHINES):
    return lambda spark, sf: layout.assign(tensor(spark, sf, name), machines, how).select("mode", "idx", "machine", "nnz")


def _counted(name: str) -> str:
    parts = " UNION ALL ".join(f"SELECT {n} AS mode, i{n} AS idx, count(*) AS nnz FROM cells GROUP BY i{n}" for n in range(1, RECIPES[name].n_modes + 1))
    return f"cells AS MATERIALIZED ({cells_sql(name)}), counts AS MATERIALIZED ({parts}), dims AS MATERIALIZED (SELECT mode, max(idx) + 1 AS length FROM counts GROUP BY mode)"


def sequential_sql(machines: int) -> str:
    """Machine m, from 1, has the rows i, from 1, with length * (m - 1) / machines < i <= length * m / machines."""
    inside = f"length * (m - 1) < (idx + 1) * {machines} AND (idx + 1) * {machines} <= length * m"
    return f"SELECT c.mode, idx, CAST(m - 1 AS INT) AS machine, nnz FROM counts c JOIN dims d ON c.mode = d.mode JOIN range(1, {machines + 1}) r(m) ON {inside}"


def random_sql(machines: int) -> str:
    place = " ".join(f"WHEN {n} THEN {portable_sql('idx', n, 0, 42)}" for n in range(1, 6))
    return f"SELECT mode, idx, CAST(floor((CASE mode {place} END) * {machines}) AS INT) AS machine, nnz FROM counts"


def greedy_steps(machines: int) -> str:
    """Row by row, heaviest first, with the machines' loads as lists: the rule itself, without classes."""
    zero = "[" + ", ".join(["CAST(0 AS BIGINT)"] * machines) + "]"
    every = f"range(1, {machines + 1})"
    pick = lambda load, held: f"list_sort(list_transform(list_filter({every}, lambda m: {held}[m] < cap), lambda m: [{load}[m], {held}[m], overall[m], m]))[1][4]"
    add = lambda name, by: f"list_transform({every}, lambda j: {name}[j] + CASE WHEN j = pick THEN {by} ELSE 0 END)"
    return (
        f"ordered AS MATERIALIZED (SELECT row_number() OVER (ORDER BY c.mode, nnz DESC, idx) AS rn, c.mode, idx, nnz, CAST(ceil(length / CAST({machines} AS DOUBLE)) AS BIGINT) AS cap FROM counts c JOIN dims d ON c.mode = d.mode), "
        f"walk AS (SELECT CAST(0 AS BIGINT) AS rn, CAST(0 AS INT) AS mode, {zero} AS loads, {zero} AS held, {zero} AS overall, CAST(0 AS BIGINT) AS pick "
        f"UNION ALL SELECT rn, mode, {add('loads', 'nnz')}, {add('held', '1')}, {add('overall', 'nnz')}, pick FROM (SELECT *, {pick('loads', 'held')} AS pick FROM ("
        f"SELECT o.rn, o.mode, o.nnz, o.cap, CASE WHEN o.mode = w.mode THEN w.loads ELSE {zero} END AS loads, CASE WHEN o.mode = w.mode THEN w.held ELSE {zero} END AS held, w.overall FROM walk w JOIN ordered o ON o.rn = w.rn + 1)))"
    )


#: Rows of equal counts are interchangeable: by index they take the machines that their class got, in order.
GREEDY = (
    "SELECT a.mode, a.idx, CAST(b.pick - 1 AS INT) AS machine, a.nnz FROM (SELECT mode, idx, nnz, row_number() OVER (PARTITION BY mode, nnz ORDER BY idx) AS k FROM ordered) a "
    "JOIN (SELECT o.mode, o.nnz, w.pick, row_number() OVER (PARTITION BY o.mode, o.nnz ORDER BY w.pick) AS k FROM walk w JOIN ordered o USING (rn)) b ON a.mode = b.mode AND a.nnz = b.nnz AND a.k = b.k"
)
QUERIES["assign_seq"] = _assigned("supply3", "sequential")
ORACLE_SQL["assign_seq"] = f"WITH {_counted('supply3')} {sequential_sql(MACHINES)}"
QUERIES["assign_random"] = _assigned("supply3", "random")
ORACLE_SQL["assign_random"] = f"WITH {_counted('supply3')} {random_sql(MACHINES)}"
QUERIES["assign_greedy"] = _assigned("supply3", "greedy")
ORACLE_SQL["assign_greedy"] = f"WITH RECURSIVE {_counted('supply3')}, {greedy_steps(MACHINES)} {GREEDY}"


def balance_compare(spark, sf):
    """Heaviest loads under the three assignments."""
    t = tensor(spark, sf, "tokens3")
    parts = []
    for how in ("sequential", "random", "greedy"):
        b = layout.balance(layout.assign(t, MACHINES, how), MACHINES)
        parts.append(b.select(F.lit(how).alias("assignment"), "mode", "max_cells", "max_rows", rounded("ratio").alias("ratio")))
    return union(parts)


def _balance_sql(how: str, rows: str) -> str:
    return f"SELECT '{how}' AS assignment, mode, CAST(max(cells) AS BIGINT) AS max_cells, CAST(max(n) AS BIGINT) AS max_rows, round(max(cells) / (sum(cells) / {float(MACHINES)}), 6) + 0.0 AS ratio FROM (SELECT mode, machine, sum(nnz) AS cells, count(*) AS n FROM ({rows}) GROUP BY 1, 2) GROUP BY mode"


QUERIES["balance_compare"] = balance_compare
ORACLE_SQL["balance_compare"] = f"WITH RECURSIVE {_counted('tokens3')}, {greedy_steps(MACHINES)} " + " UNION ALL ".join([_balance_sql("sequential", sequential_sql(MACHINES)), _balance_sql("random", random_sql(MACHINES)), _balance_sql("greedy", GREEDY)])

QUERIES["mode_copy_sizes"] = lambda spark, sf: layout.mode_copy_sizes(tensor(spark, sf, "supply3"), layout.assign(tensor(spark, sf, "supply3"), MACHINES, "sequential"))
ORACLE_SQL["mode_copy_sizes"] = f"WITH {_counted('supply3')} SELECT mode, machine, CAST(sum(nnz) AS BIGINT) AS cells FROM ({sequential_sql(MACHINES)}) GROUP BY 1, 2"


def strata_schedule(spark, sf):
    """Blocks of every stratum of the event tensor, with their cells, for 2 machines and for 3 machines."""
    t, parts = tensor(spark, sf, "events3"), []
    for m in (2, 3):
        held = layout.with_blocks(t, m).groupBy("b1", "b2", "b3").agg(F.count("*").alias("cells"))
        every = layout.strata(spark, m, 3).join(held, ["b1", "b2", "b3"], "left")
        parts.append(every.select(F.lit(m).alias("machines"), "stratum", "m", "b1", "b2", "b3", F.coalesce("cells", F.lit(0)).alias("cells")))
    return union(parts)


QUERIES["strata_schedule"] = strata_schedule
_EVERY = " UNION ALL ".join(f"SELECT {m} AS machines, s AS stratum, CAST(b AS INT) AS m, CAST(b AS INT) AS b1, CAST((b + s // {m}) % {m} AS INT) AS b2, CAST((b + s % {m}) % {m} AS INT) AS b3 FROM range({m * m}) a(s), range({m}) c(b)" for m in (2, 3))
_HELD = " UNION ALL ".join(f"SELECT {m} AS machines, " + ", ".join(f"CAST(((i{n} + 1) * {m} - 1) // (SELECT max(i{n}) + 1 FROM cells) AS INT) AS b{n}" for n in (1, 2, 3)) + " FROM cells" for m in (2, 3))
ORACLE_SQL["strata_schedule"] = f"WITH cells AS MATERIALIZED ({cells_sql('events3')}), held AS (SELECT machines, b1, b2, b3, count(*) AS cells FROM ({_HELD}) GROUP BY ALL) SELECT e.*, coalesce(cells, 0) AS cells FROM ({_EVERY}) e LEFT JOIN held USING (machines, b1, b2, b3)"
QUERIES["strata_cells"] = lambda spark, sf: layout.with_blocks(tensor(spark, sf, "events3"), 2).groupBy("stratum", "b1", "b2", "b3").agg(F.count("*").alias("cells"))
#: Of two machines the first has the rows i, from 1, with i <= length / 2.
_B = [f"CASE WHEN (i{n} + 1) * 2 <= (SELECT max(i{n}) + 1 FROM cells) THEN 0 ELSE 1 END" for n in (1, 2, 3)]
ORACLE_SQL["strata_cells"] = f"WITH cells AS MATERIALIZED ({cells_sql('events3')}), blocks AS (SELECT {_B[0]} AS b1, {_B[1]} AS b2, {_B[2]} AS b3 FROM cells) SELECT CAST(((b2 - b1 + 2) % 2) * 2 + (b3 - b1 + 2) % 2 AS BIGINT) AS stratum, b1, b2, b3, count(*) AS cells FROM blocks GROUP BY ALL"
