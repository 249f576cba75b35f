"""Shared plumbing of the corpus operators: table access, Arrow text buffers, word hashing, written tables."""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one vectorised step handles: bounds the kernels' memory and keeps their arrays in the cache.
CHUNK_BYTES = 1 << 19
#: Separators of words: space and the control characters tab to carriage return.
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True

_SHIPPED: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Send this package's sources to the executors once per application, so that Python workers can import it."""
    context = spark.sparkContext
    if context.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parents[2]
    target = Path(tempfile.mkdtemp(prefix="ship_")) / "cubefactor_sources.zip"
    with zipfile.ZipFile(target, "w") as archive:
        for path in sorted((root / "cubefactor").rglob("*.py")):
            archive.write(path, path.relative_to(root))
    context.addPyFile(str(target))
    _SHIPPED.add(context.applicationId)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a local one where a session on one machine sets none."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    fallback = os.path.join(tempfile.gettempdir(), "cubefactor-checkpoints")
    os.makedirs(fallback, exist_ok=True)
    return f"file://{fallback}"


def written(frame: DataFrame, name: str, codec: str = "snappy") -> DataFrame:
    """Cut the lineage through a Parquet table in the shared folder; survives the loss of executors.

    `zstd` suits large texts; its native buffers outlive many small files in the executors' memory.
    """
    spark = frame.sparkSession
    ship_package(spark)
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    frame.write.option("compression", codec).parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


def unused(frame: DataFrame, stem: str) -> str:
    """A column name that the frame doesn't have, whatever its columns are called."""
    taken = {c.lower() for c in frame.columns}
    while stem.lower() in taken:
        stem += "_"
    return stem


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def crc_fold(doc_id: Column, modulus: int) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % F.lit(modulus)


def text_buffer(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and n+1 offsets of a string or binary array, without copying; nulls count as empty."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    if array.null_count:
        array = array.fill_null(b"" if pa.types.is_binary(array.type) or pa.types.is_large_binary(array.type) else "")
    wide = pa.types.is_large_string(array.type) or pa.types.is_large_binary(array.type)
    _, offsets, data = array.buffers()
    if offsets is None or len(array) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(array) + 1, np.int64)
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[array.offset : array.offset + len(array) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def release_memory() -> None:
    """Give freed memory back to the system: Python workers outlive their tasks and wait beside the next stage's."""
    pa.default_memory_pool().release_unused()
    gc.collect()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library: nothing to trim


def chunks(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of the batches that hold about `limit` bytes of text each, and one row at least."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        _, offsets = text_buffer(batch.column(batch.schema.get_field_index(column)))
        start = 0
        while start < batch.num_rows:
            stop = int(np.searchsorted(offsets, offsets[start] + limit, "right")) - 1
            stop = min(max(stop, start + 1), batch.num_rows)
            yield batch.slice(start, stop - start)
            start = stop
    release_memory()


def mix64(values: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers (the finaliser of a well-known public hash)."""
    values = values.astype(np.uint64, copy=True)
    values ^= values >> np.uint64(33)
    values *= np.uint64(0xFF51AFD7ED558CCD)
    values ^= values >> np.uint64(33)
    values *= np.uint64(0xC4CEB9FE1A85EC53)
    values ^= values >> np.uint64(33)
    return values


_BYTE_CODES = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_RADIX = np.uint64(0xD6E8FEB86659FD93)
_POWERS = np.ones(1, np.uint64)


def powers(count: int) -> np.ndarray:
    """Powers of the odd radix modulo 2**64, at least `count` of them."""
    global _POWERS
    if len(_POWERS) < count:
        size = max(count, 2 * len(_POWERS), 1024)
        _POWERS = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(size - 1, _RADIX, np.uint64))])
    return _POWERS


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte span; spans must be ordered and must not overlap."""
    if len(starts) == 0:
        return np.zeros(0, np.uint64)
    lengths = ends - starts
    inside = np.repeat(starts - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths) + np.arange(int(lengths.sum()))
    rank = inside - np.repeat(starts, lengths)
    coded = _BYTE_CODES[data[inside]] * powers(int(lengths.max()) + 1)[rank]
    sums = np.zeros(len(starts), np.uint64)
    some = lengths > 0
    if some.any():
        first = np.concatenate([[0], np.cumsum(lengths)[:-1]])
        sums[some] = np.add.reduceat(coded, first[some])
    return mix64(sums ^ (lengths.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words, and the number of the row that each lies in; words end at row ends."""
    if len(data) == 0:
        return (np.zeros(0, np.int64),) * 3
    solid = ~IS_SPACE[data]
    begins = solid.copy()
    begins[1:] &= ~solid[:-1]
    heads = offsets[:-1][offsets[:-1] < offsets[1:]]
    begins[heads] = solid[heads]
    closes = solid.copy()
    closes[:-1] &= ~solid[1:]
    tails = heads[heads > 0] - 1
    closes[tails] = solid[tails]
    starts, ends = np.flatnonzero(begins), np.flatnonzero(closes) + 1
    return starts, ends, np.searchsorted(offsets, starts, "right") - 1


def row_bounds(row: np.ndarray, rows: int) -> np.ndarray:
    """n+1 bounds of the runs of each row number in a sorted array."""
    return np.searchsorted(row, np.arange(rows + 1))


def row_hash(docs: DataFrame) -> Column:
    return F.xxhash64(*(F.col(f"`{c}`") for c in docs.columns))


def keep_least(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """One row of `docs` per group (rows doc_id, tie, grp): that of the smallest (doc_id, tie); rows without doc_id stay."""
    counted = written(groups.groupBy("grp", "doc_id", "tie").agg(F.count("*").alias("n")), "group-rows")
    least = counted.groupBy("grp").agg(F.min(F.struct("doc_id", "tie")).alias("least")).withColumnRenamed("grp", "of")
    at, tie = unused(docs, "_least"), unused(docs, "_tie")
    other = counted.join(least, F.col("grp") == F.col("of")).withColumn("goes", F.struct("doc_id", "tie") != F.col("least"))
    marked = written(other.where("goes OR n > 1").select(F.col("doc_id").alias(at), F.col("tie").alias(tie), "goes").distinct(), "group-others")
    same = lambda side: (F.col("doc_id").cast("long") == side[at]) & (row_hash(docs) == side[tie])
    gone = marked.select(at, tie)
    stay = docs.join(gone, same(gone), "left_anti")
    again = marked.where("NOT goes").select(at, tie)
    if again.isEmpty():
        return stay
    # Repeated rows that are their group's least, all columns alike: one stays.
    once = docs.join(again, same(again)).dropDuplicates([at, tie]).select(*(F.col(f"`{c}`") for c in docs.columns))
    return stay.unionByName(once)


def arrow_like(schema: pa.Schema, columns: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in schema], schema=schema)
