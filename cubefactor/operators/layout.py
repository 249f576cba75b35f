"""Where rows and cells live: row assignment, balance, mode copies, blocks and strata."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from ..plans import planner
from .tensor import TensorFrame, mode_counts, portable


def block(idx: Column, length: Column | int, machines: int) -> Column:
    """The range that an index lies in, of `machines` ranges that differ by one row at most: none is empty
    unless there are fewer rows than machines."""
    size = F.lit(length) if isinstance(length, int) else length
    return F.floor(((idx + 1) * machines - 1) / size).cast("int")


def lengths(dims: list[int], mode: str = "mode") -> Column:
    return F.element_at(F.array(*map(F.lit, dims)), F.col(mode))


def assign_sequential(counts: DataFrame, dims: list[int], machines: int) -> DataFrame:
    """(mode, idx, machine, nnz): contiguous ranges of rows, equal but for one row."""
    return counts.select("mode", "idx", block(F.col("idx"), lengths(dims), machines).alias("machine"), "nnz")


def assign_random(counts: DataFrame, dims: list[int], machines: int, seed: int = 42) -> DataFrame:
    """(mode, idx, machine, nnz): a hash of the row, another one in each mode."""
    place = reduce(lambda other, n: F.when(F.col("mode") == n, portable(F.col("idx"), n, 0, seed)).otherwise(other), range(1, len(dims) + 1), F.lit(0.0))
    return counts.select("mode", "idx", F.floor(place * machines).cast("int").alias("machine"), "nnz")


def greedy_classes(classes: list[tuple[int, int]], machines: int, capacity: int, overall: list[int]) -> list[tuple[int, int, int]]:
    """(nnz, machine, how many) for rows grouped by equal counts, heaviest class first.

    Each row goes to the machine of least load that has room; ties go to fewer rows, then to the smaller load
    over all modes so far, then to the smaller number. Equal rows are interchangeable, so a class is placed as
    a whole: a machine takes its rows at loads that grow by the class's weight, and the least of those loads
    over all machines are found by halving. A class costs the logarithm of its size, not its size.
    """
    load, held, total = np.zeros(machines, np.int64), np.zeros(machines, np.int64), np.array(overall, np.int64)
    out = []
    for weight, rows in sorted(classes, reverse=True):
        room = capacity - held
        below = lambda level: np.clip(-(-(level - load) // weight), 0, room)  # noqa: B023, E731 - rows taken at loads under the level
        low, high = 0, int(load.max()) + weight * (rows + 1)
        while low < high:  # the highest level with no more rows than there are
            middle = (low + high + 1) // 2
            low, high = (middle, high) if below(middle).sum() <= rows else (low, middle - 1)
        taken = below(low)
        left = rows - int(taken.sum())
        if left:  # some of the machines that stand at the level itself
            at_level = np.flatnonzero((load + taken * weight == low) & (taken < room))
            ranked = at_level[np.lexsort((at_level, (total + taken * weight)[at_level], (held + taken)[at_level]))]
            taken[ranked[:left]] += 1
        load += taken * weight
        held += taken
        total += taken * weight
        out += [(weight, int(m), int(taken[m])) for m in np.flatnonzero(taken)]
    overall[:] = total.tolist()
    return out


def assign_greedy(counts: DataFrame, dims: list[int], machines: int) -> DataFrame:
    """(mode, idx, machine, nnz): heaviest rows first to the least loaded machine with room.

    Rows with no cell are not in `counts` and weigh nothing. Rows of a class are numbered by index and take
    the class's machines in order. The driver sees one row per distinct count, never a row per index.
    """
    spark = counts.sparkSession
    histogram = counts.groupBy("mode", "nnz").count().collect()
    overall, plan = [0] * machines, []
    for mode, length in enumerate(dims, 1):
        classes = [(r["nnz"], r["count"]) for r in histogram if r["mode"] == mode]
        first: dict[int, int] = {}
        for weight, machine, rows in greedy_classes(classes, machines, -(-length // machines), overall):
            begin = first.get(weight, 0)
            plan.append((mode, weight, machine, begin, begin + rows))
            first[weight] = begin + rows
    places = spark.createDataFrame(plan, "pmode int, weight long, machine int, first long, stop long")
    ranked = ranked_in_class(counts)
    hit = (F.col("mode") == F.col("pmode")) & (F.col("nnz") == F.col("weight")) & (F.col("at") >= F.col("first")) & (F.col("at") < F.col("stop"))
    return ranked.join(F.broadcast(places) if planner.fits_broadcast(len(plan), 5) else places, hit).select("mode", "idx", "machine", "nnz")


def ranked_in_class(counts: DataFrame, width: int = 1 << 16) -> DataFrame:
    """`at`: the row's number, by index, within its mode and count, without gathering a class in one task.

    Ranges of `width` indices are numbered apart; their row counts give each range its first number.
    """
    from pyspark.sql.window import Window

    ranged = counts.withColumn("range", F.floor(F.col("idx") / width))
    sizes = ranged.groupBy("mode", "nnz", "range").count()
    before = Window.partitionBy("mode", "nnz").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    firsts = sizes.select(F.col("mode").alias("_m"), F.col("nnz").alias("_n"), F.col("range").alias("_r"), F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))
    inner = ranged.withColumn("own", F.row_number().over(Window.partitionBy("mode", "nnz", "range").orderBy("idx")) - 1)
    joined = inner.join(firsts, (F.col("mode") == F.col("_m")) & (F.col("nnz") == F.col("_n")) & (F.col("range") == F.col("_r")))
    return joined.select("mode", "idx", "nnz", (F.col("own") + F.col("base")).alias("at"))


def assign(tensor: TensorFrame, machines: int, assignment: str = "greedy", seed: int = 42) -> DataFrame:
    counts = mode_counts(tensor)
    if assignment == "sequential":
        return assign_sequential(counts, tensor.dims, machines)
    if assignment == "random":
        return assign_random(counts, tensor.dims, machines, seed)
    if assignment == "greedy":
        return assign_greedy(counts, tensor.dims, machines)
    raise ValueError(f"unknown assignment {assignment!r}")


def balance(assigned: DataFrame, machines: int) -> DataFrame:
    """Per mode: heaviest and mean load in cells and rows, and the ratio that bounds the speed of a step."""
    loads = assigned.groupBy("mode", "machine").agg(F.sum("nnz").alias("cells"), F.count("*").alias("rows"))
    mean = F.sum("cells") / F.lit(float(machines))
    return loads.groupBy("mode").agg(F.max("cells").cast("long").alias("max_cells"), mean.alias("mean_cells"), F.max("rows").cast("long").alias("max_rows"), (F.max("cells") / mean).alias("ratio"))


def owners(cells: DataFrame, assigned: DataFrame, mode: int, name: str, length: int) -> DataFrame:
    """Cells with the machine that owns their row of a mode; a long mode's owners are joined by a shuffle."""
    side = assigned.where(F.col("mode") == mode).select(F.col("idx").alias("_idx"), F.col("machine").alias(name))
    return cells.join(F.broadcast(side) if planner.fits_broadcast(length, 2) else side, F.col(f"i{mode}") == F.col("_idx")).drop("_idx")


def distribute(cells: DataFrame, assigned: DataFrame, mode: int, machines: int, length: int | None = None) -> DataFrame:
    """The copy of the cells for a mode: each machine's partition holds the cells of its rows, sorted by row, on disk.

    The partition of a row is its machine itself, so a grouping by (machine, row) needs no further shuffle.
    `length` is the mode's length, counted if it isn't given: it decides how the owners are joined.
    """
    rows = assigned.where(F.col("mode") == mode).count() if length is None else length
    placed = owners(cells, assigned, mode, "machine", rows)
    return placed.repartitionById(machines, "machine").sortWithinPartitions(f"i{mode}").persist(StorageLevel.DISK_ONLY)


def mode_copy_sizes(tensor: TensorFrame, assigned: DataFrame) -> DataFrame:
    """(mode, machine, cells): what each machine stores; the sum over modes is the number of modes times the cells."""
    return assigned.groupBy("mode", "machine").agg(F.sum("nnz").cast("long").alias("cells"))


def with_blocks(tensor: TensorFrame, machines: int, assigned: DataFrame | None = None) -> DataFrame:
    """Cells with their block per mode and their stratum: the shifts of the other modes' blocks against mode 1's.

    Blocks are the machines that own the rows where an assignment is given, else equal ranges.
    """
    cells = tensor.cells
    for n, (m, d) in enumerate(zip(tensor.modes, tensor.dims, strict=True), 1):
        cells = cells.withColumn(f"b{n}", block(F.col(m), d, machines)) if assigned is None else owners(cells, assigned, n, f"b{n}", d)
    digits = [F.pmod(F.col(f"b{n}") - F.col("b1"), F.lit(machines)) for n in range(2, tensor.n_modes + 1)]
    return cells.withColumn("stratum", reduce(lambda a, b: a * machines + b, digits, F.lit(0)).cast("long"))


def strata(spark: SparkSession, machines: int, n_modes: int) -> DataFrame:
    """(stratum, m, b1..bN): the blocks of each stratum; no two share a row in any mode, and all strata cover every block once."""
    each = spark.range(machines ** (n_modes - 1) * machines).select(F.expr(f"id div {machines}").alias("stratum"), F.pmod("id", F.lit(machines)).cast("int").alias("m"))
    shifts = [F.pmod(F.expr(f"stratum div {machines ** (n_modes - n)}"), F.lit(machines)) for n in range(2, n_modes + 1)]
    return each.select("stratum", "m", F.col("m").alias("b1"), *(F.pmod(F.col("m") + s, F.lit(machines)).cast("int").alias(f"b{n}") for n, s in enumerate(shifts, 2)))
