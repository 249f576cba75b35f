"""Sparse tensors as DataFrames of cells, built from any fact table."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .lineage import written

#: Modulus (a prime under 2**31, so that products stay in 64 bits) and factors of the portable hash (fixed values).
P, A, B, C, D = 2_147_483_647, 48_271, 1_583_458_089, 784_588_716, 1_226_874_159
#: Factors of the modes' indices in the hash of a tuple (fixed values).
TUPLE = (48_271, 69_621, 630_360_016, 742_938_285, 950_706_376, 1_226_874_159, 62_089_911)


def _shift(mode: int, component: int, seed: int) -> int:
    return (mode * B + component * C + seed * D) % P


def _cubed(value: Column) -> Column:
    """A cubic polynomial modulo P: consecutive values land apart, and nothing repeats before P."""
    return F.pmod(value * F.pmod(value * value + C, F.lit(P)), F.lit(P))


def _cubed_sql(value: str) -> str:
    return f"list_transform([{value}], lambda y: (y * ((y * y + {C}) % {P})) % {P})[1]"


def portable(idx: Column, mode: int, component: int = 0, seed: int = 42) -> Column:
    """A double in [0, 1) from integer arithmetic alone, so that other engines get the same; its period is P."""
    y = F.pmod(F.pmod(idx.cast("long"), F.lit(P)) * A + F.lit(_shift(mode, component, seed)), F.lit(P))
    return _cubed(y).cast("double") / F.lit(float(P))


def portable_sql(idx: str, mode: int, component: int = 0, seed: int = 42) -> str:
    y = f"((CAST({idx} AS BIGINT) % {P}) * {A} + {_shift(mode, component, seed)}) % {P}"
    return f"CAST({_cubed_sql(y)} AS DOUBLE) / {float(P)}"


@dataclass
class TensorFrame:
    """Observed cells (i1..iN, x), mode lengths, and the dictionaries that give the indices' keys."""

    cells: DataFrame
    dims: list[int]
    dictionaries: list[DataFrame] = field(default_factory=list)

    @property
    def n_modes(self) -> int:
        return len(self.dims)

    @property
    def modes(self) -> list[str]:
        return [f"i{n}" for n in range(1, self.n_modes + 1)]


def raw_cells(source: DataFrame, keys: list[Column], value: Column, where: Column | None = None) -> DataFrame:
    """(k1..kN, x): one row per observed tuple; `value` aggregates repeated tuples; null keys and values go.

    Missing cells stay missing: they are unobserved, not zero.
    """
    names = [f"k{n}" for n in range(1, len(keys) + 1)]
    rows = source if where is None else source.where(where)
    grouped = rows.groupBy(*(k.alias(n) for k, n in zip(keys, names, strict=True))).agg(value.cast("double").alias("x"))
    fine = reduce(lambda a, b: a & b, [F.col(n).isNotNull() for n in names]) & F.col("x").isNotNull() & ~F.isnan("x")
    return grouped.where(fine)


def dictionary(raw: DataFrame, mode: int) -> DataFrame:
    """(key, idx, nnz) of a mode, idx from 0 in key order, without gathering the keys in one task.

    Keys are range-partitioned and sorted; partitions' row counts, one per partition, give the offsets.
    """
    keys = raw.groupBy(F.col(f"k{mode}").alias("key")).agg(F.count("*").alias("nnz"))
    placed = written(keys.repartitionByRange("key").sortWithinPartitions("key").withColumn("at", F.monotonically_increasing_id()), "dictionary")
    part = F.shiftright("at", 33)
    sizes = sorted((r["part"], r["count"]) for r in placed.groupBy(part.alias("part")).count().collect())
    offsets, total = {}, 0
    for number, count in sizes:
        offsets[number] = total
        total += count
    if len(offsets) > 1:
        base = F.element_at(F.create_map(*(F.lit(v) for pair in offsets.items() for v in pair)), part)
    else:
        base = F.lit(0)
    return placed.select("key", (base + F.col("at").bitwiseAND(F.lit((1 << 33) - 1))).cast("long").alias("idx"), "nnz")


def encode(raw: DataFrame, n_modes: int) -> TensorFrame:
    """A tensor with dense indices from 0 for the keys of `raw`."""
    base = written(raw, "raw-cells")
    dictionaries = [dictionary(base, n) for n in range(1, n_modes + 1)]
    cells = base
    for n, entries in enumerate(dictionaries, 1):
        cells = cells.join(entries.select(F.col("key").alias(f"k{n}"), F.col("idx").alias(f"i{n}")), f"k{n}")
    cells = written(cells.select(*(f"i{n}" for n in range(1, n_modes + 1)), "x"), "cells")
    return TensorFrame(cells, [d.count() for d in dictionaries], dictionaries)


def decode(cells: DataFrame, tensor: TensorFrame) -> DataFrame:
    """Keys k1..kN instead of indices."""
    for n, entries in enumerate(tensor.dictionaries, 1):
        cells = cells.join(entries.select(F.col("idx").alias(f"i{n}"), F.col("key").alias(f"k{n}")), f"i{n}").drop(f"i{n}")
    return cells


def validate(cells: DataFrame, dims: list[int]) -> DataFrame:
    """One row of counts: cells, nulls, NaNs, indices out of bounds, repeated tuples."""
    modes = [f"i{n}" for n in range(1, len(dims) + 1)]
    outside = reduce(lambda a, b: a | b, [(F.col(m) < 0) | (F.col(m) >= d) for m, d in zip(modes, dims, strict=True)])
    absent = reduce(lambda a, b: a | b, [F.col(m).isNull() for m in [*modes, "x"]])
    once = cells.groupBy(*modes).agg(F.count("*").alias("n"), F.sum(absent.cast("long")).alias("nulls"), F.sum(F.coalesce(F.isnan("x"), F.lit(False)).cast("long")).alias("nans"), F.sum(F.coalesce(outside, F.lit(False)).cast("long")).alias("outside"))
    zero = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    return once.agg(zero("n").alias("cells"), zero("nulls").alias("nulls"), zero("nans").alias("nans"), zero("outside").alias("out_of_bounds"), zero(F.col("n") - 1).alias("repeated"))


def mode_counts(tensor: TensorFrame) -> DataFrame:
    """(mode, idx, nnz): observed cells of every row of every mode, in one pass."""
    copies = F.explode(F.array(*(F.struct(F.lit(n).alias("mode"), F.col(m).alias("idx")) for n, m in enumerate(tensor.modes, 1))))
    return tensor.cells.select(copies.alias("c")).groupBy(F.col("c.mode").alias("mode"), F.col("c.idx").alias("idx")).agg(F.count("*").alias("nnz"))


def held_out(tensor: TensorFrame, share: int = 10) -> Column:
    """True for one of `share` cells, by a portable hash of the tuple."""
    total = reduce(lambda a, b: a + b, [F.pmod(F.col(m) * f, F.lit(P)) for m, f in zip(tensor.modes, TUPLE, strict=False)])
    return F.pmod(_cubed(F.pmod(total, F.lit(P))), F.lit(share)) == 0


def held_out_sql(modes: list[str], share: int = 10) -> str:
    total = " + ".join(f"(CAST({m} AS BIGINT) * {f}) % {P}" for m, f in zip(modes, TUPLE, strict=False))
    return f"({_cubed_sql(f'({total}) % {P}')}) % {share} = 0"


def split(tensor: TensorFrame, share: int = 10) -> tuple[TensorFrame, DataFrame]:
    """Training tensor and held-out cells."""
    mark = held_out(tensor, share)
    return TensorFrame(tensor.cells.where(~mark), tensor.dims, tensor.dictionaries), tensor.cells.where(mark)


def fix_mode(tensor: TensorFrame, mode: int, idx: int) -> TensorFrame:
    """The slice at one index of a mode: a tensor with one mode less."""
    rest = [m for n, m in enumerate(tensor.modes, 1) if n != mode]
    names = [f"i{n}" for n in range(1, len(rest) + 1)]
    cells = tensor.cells.where(F.col(f"i{mode}") == idx).select(*(F.col(m).alias(n) for m, n in zip(rest, names, strict=True)), "x")
    return TensorFrame(cells, [d for n, d in enumerate(tensor.dims, 1) if n != mode])


def marginalize(tensor: TensorFrame, keep: list[int], agg: str = "sum") -> TensorFrame:
    """Cells aggregated over the other modes."""
    names = [f"i{n}" for n in range(1, len(keep) + 1)]
    grouped = tensor.cells.groupBy(*(F.col(f"i{k}").alias(n) for k, n in zip(keep, names, strict=True))).agg(getattr(F, agg)("x").cast("double").alias("x"))
    return TensorFrame(grouped, [tensor.dims[k - 1] for k in keep])


def unfold(tensor: TensorFrame, mode: int) -> TensorFrame:
    """The matrix whose rows are a mode and whose columns are the other modes in mixed radix."""
    column, width = F.lit(0).cast("long"), 1
    for n, (m, d) in enumerate(zip(tensor.modes, tensor.dims, strict=True), 1):
        if n != mode:
            column = column + F.col(m) * width
            width *= d
    return TensorFrame(tensor.cells.select(F.col(f"i{mode}").alias("i1"), column.alias("i2"), "x"), [tensor.dims[mode - 1], width])


def permute(tensor: TensorFrame, order: list[int]) -> TensorFrame:
    cells = tensor.cells.select(*(F.col(f"i{o}").alias(f"i{n}") for n, o in enumerate(order, 1)), "x")
    return TensorFrame(cells, [tensor.dims[o - 1] for o in order], [tensor.dictionaries[o - 1] for o in order] if tensor.dictionaries else [])


def rescale(tensor: TensorFrame, shift: float = 0.0, factor: float = 1.0) -> TensorFrame:
    return TensorFrame(tensor.cells.withColumn("x", (F.col("x") - shift) * factor), tensor.dims, tensor.dictionaries)


def combine(left: TensorFrame, right: TensorFrame, sign: int = 1) -> TensorFrame:
    """Sum or difference on the common support."""
    other = right.cells.withColumnRenamed("x", "y")
    return TensorFrame(left.cells.join(other, left.modes).withColumn("x", F.col("x") + sign * F.col("y")).drop("y"), left.dims, left.dictionaries)
