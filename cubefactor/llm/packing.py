"""Packing by cutting-stock column generation.

Every document is tokenized once. Its tokens are cut into whole sequences of `capacity`, then into a stem
of whole `unit`s and a tail shorter than a unit. A linear program over the histogram of stem sizes finds
how often each pattern of stems fills a sequence: new patterns (columns) are priced by an unbounded
knapsack dynamic program until none lowers the number of sequences. Patterns are used a whole number of
times (rounded down); stems left over are packed best-fit-decreasing by count. Stems are ranked within
their size and the table of patterns tells each rank its sequence and offset. Tails follow one another in a
stream that is cut wherever a sequence is full; what is left at its end is cut into powers of two, which
need no padding.

Only the histogram (at most capacity / unit sizes and `unit` tail sizes) reaches the driver, and only the
pattern table (bounded by the sizes squared) is sent back: both are independent of the number of documents.

Defined cases: a null or empty text is the end token alone; texts of any length are packed whole; repeated
rows are packed as separate documents; a null doc_id is packed like any other; an empty table gives no
rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .bpe import WordMerger, distinct_spans, simple_spans
from .common import chunks, text_buffer, text_or_empty, written

CAPACITY, UNIT, END_ID = 4096, 32, 2
_TOKENIZERS: dict[str, object] = {}
_MERGERS: dict[str, WordMerger] = {}


def _tokenizer(path: str):
    if path not in _TOKENIZERS:
        from tokenizers import Tokenizer

        _TOKENIZERS[path] = Tokenizer.from_file(path)
    return _TOKENIZERS[path]


def _merger(path: str) -> WordMerger:
    if path not in _MERGERS:
        _MERGERS[path] = WordMerger(path)
    return _MERGERS[path]


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def token_ids(texts: pa.Array, path: str, end_id: int = END_ID) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts, each closed by the end token, and n+1 offsets; distinct words are encoded once.

    Plain words are merged in numpy (see `bpe`), the others by the tokenizer's library.
    """
    data, bounds = text_buffer(texts)
    low, starts, ends, library, row = simple_spans(data, bounds)
    first, kind = distinct_spans(low, data, starts, ends, library)
    by_library = library[first]
    sizes = np.zeros(len(first), np.int64)
    plain = first[~by_library]
    flat, sizes[~by_library] = _merger(path).encode(low, starts[plain], ends[plain])
    rare = first[by_library]
    words = [data[a:b].tobytes().decode() for a, b in zip(starts[rare].tolist(), ends[rare].tolist(), strict=True)]
    got = [np.array(e.ids, np.int64) for e in _tokenizer(path).encode_batch_fast(words, add_special_tokens=False)] if words else []
    sizes[by_library] = [len(g) for g in got]
    begins = np.zeros(len(first), np.int64)
    begins[~by_library] = np.cumsum(sizes[~by_library]) - sizes[~by_library]
    begins[by_library] = len(flat) + np.cumsum(sizes[by_library]) - sizes[by_library]
    flat = np.concatenate([flat, *got]).astype(np.uint32)
    lengths = sizes[kind]
    stops = np.concatenate([[0], np.cumsum(lengths)])
    words_before = np.searchsorted(row, np.arange(len(bounds)))
    offsets = stops[words_before] + np.arange(len(bounds))  # one end token after each text
    ids = np.full(int(offsets[-1]), end_id, np.uint32)
    source = np.repeat(begins[kind] - stops[:-1], lengths) + np.arange(int(stops[-1]))
    target = np.repeat(row, lengths) + np.arange(int(stops[-1]))
    ids[target] = flat[source]
    return ids, offsets


def cut_pieces(docs: DataFrame, *, tokenizer: str, capacity: int = CAPACITY, unit: int = UNIT, end_id: int = END_ID) -> DataFrame:
    """Every piece of every document: whole sequences, stem and tail; a tail carries its ids, as it may be cut again."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, limit=1 << 20):
            ids, offsets = token_ids(part.column(1), tokenizer, end_id)
            raw = memoryview(ids.astype("<u4").tobytes())
            doc, start, length, crc, total, small = [], [], [], [], [], []
            for doc_id, a, b in zip(part.column(0).to_pylist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                n = b - a
                whole = n // capacity * capacity
                stem = whole + (n - whole) // unit * unit
                for at, to in [*((x, x + capacity) for x in range(0, whole, capacity)), (whole, stem), (stem, n)]:
                    if to > at:
                        doc.append(doc_id)
                        start.append(at)
                        length.append(to - at)
                        crc.append(zlib.crc32(raw[4 * (a + at) : 4 * (a + to)]))
                        total.append(n)
                        small.append(bytes(raw[4 * (a + at) : 4 * (a + to)]) if to - at < unit else None)
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in (doc, start, length, crc, total)), pa.array(small, pa.binary())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "tail_ids"])

    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, tail_ids binary")


def best_pattern(prices: np.ndarray, sizes: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """The most valuable multiset of sizes that fits the room (unbounded knapsack by dynamic programming)."""
    value, pick = np.zeros(room + 1), np.full(room + 1, -1)
    for at in range(1, room + 1):
        fits = np.flatnonzero(sizes <= at)
        value[at] = value[at - 1]
        if len(fits):
            gains = prices[fits] + value[at - sizes[fits]]
            k = int(gains.argmax())
            if gains[k] > value[at] + 1e-12:
                value[at], pick[at] = gains[k], fits[k]
    counts, at = np.zeros(len(sizes), np.int64), room
    while at > 0:
        if pick[at] < 0:
            at -= 1
            continue
        counts[pick[at]] += 1
        at -= sizes[pick[at]]
    return float(value[room]), counts


def _inverted(matrix: np.ndarray) -> np.ndarray:
    """Gauss-Jordan inverse in plain array operations: the driver calls no threaded linear algebra."""
    n = len(matrix)
    table = np.hstack([matrix.astype(float), np.eye(n)])
    for k in range(n):
        top = k + int(np.abs(table[k:, k]).argmax())
        table[[k, top]] = table[[top, k]]
        table[k] /= table[k, k]
        others = np.arange(n) != k
        table[others] -= np.outer(table[others, k], table[k])
    return table[:, n:]


def cutting_stock(sizes: np.ndarray, demand: np.ndarray, room: int, *, most_columns: int = 2000, slack: float = 1e-7) -> tuple[np.ndarray, np.ndarray]:
    """Patterns (columns) and how often the linear program uses each, by the revised simplex method.

    The basis starts with one pattern for each size, as often as it fits; duals price new patterns.
    """
    n = len(sizes)
    columns = np.diag(room // sizes).astype(float)
    inverse = np.diag(1.0 / np.diag(columns))
    level = (inverse * demand).sum(1)
    for turn in range(most_columns):
        if turn % 50 == 49:  # restores precision
            inverse = _inverted(columns)
            level = (inverse * demand).sum(1)
        prices = inverse.sum(0)
        worth, pattern = best_pattern(prices, sizes, room)
        total = level.sum()
        if worth <= 1 + slack or math.ceil(total / worth - slack) >= math.ceil(total - slack):
            break  # no better column, or none that could save a whole sequence: total / worth bounds the optimum from below
        direction = (inverse * pattern).sum(1)
        grows = direction > 1e-9
        if not grows.any():
            break
        ratio = np.where(grows, np.maximum(level, 0) / np.where(grows, direction, 1), np.inf)
        leave = int(ratio.argmin())
        step = ratio[leave]
        level -= step * direction
        level[leave] = step
        inverse[leave] /= direction[leave]
        others = np.arange(n) != leave
        inverse[others] -= np.outer(direction[others], inverse[leave])
        columns[:, leave] = pattern
    return columns.astype(np.int64), np.maximum(level, 0)


def plan_patterns(histogram: dict[int, int], room: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Runs of (how many sequences, stems in each as (size, count)) that hold every stem of the histogram exactly once.

    Rounded-down patterns come first; the rest is packed best fit, largest sizes first, with equal sequences as one run.
    """
    sizes = np.array(sorted(histogram, reverse=True), np.int64)
    if not len(sizes):
        return []
    left = np.array([histogram[int(s)] for s in sizes], np.int64)
    columns, level = cutting_stock(sizes, left.astype(float), room)
    runs = []
    for k in np.argsort(-level, kind="stable"):
        pattern = columns[:, k]
        used = np.flatnonzero(pattern)
        times = min(int(math.floor(level[k] + 1e-6)), int((left[used] // pattern[used]).min()) if len(used) else 0)
        if times > 0:
            runs.append((times, [(int(sizes[i]), int(pattern[i])) for i in used]))
            left -= times * pattern
    while left.any():
        space, filling = room, []
        for i in np.flatnonzero(left):
            fit = min(int(left[i]), space // int(sizes[i]))
            if fit:
                filling.append((i, fit))
                space -= fit * int(sizes[i])
        times = min(int(left[i]) // k for i, k in filling)
        for i, k in filling:
            left[i] -= times * k
        runs.append((times, [(int(sizes[i]), k) for i, k in filling]))
    return runs


def pattern_table(runs: list[tuple[int, list[tuple[int, int]]]], unit: int) -> list[tuple[int, int, int, int, int, int]]:
    """Rows (size, first_rank, ranks, per_sequence, first_sequence, first_offset): which sequence each rank of a size is in."""
    used: dict[int, int] = {}
    rows, sequence = [], 0
    for times, stems in runs:
        offset = 0
        for size, count in stems:
            first = used.get(size, 0)
            rows.append((size * unit, first, times * count, count, sequence, offset))
            used[size] = first + times * count
            offset += size * count * unit
        sequence += times
    return rows


def ranked(pieces: DataFrame, key: str) -> DataFrame:
    """`rank` from 0 within each key, ordered by bucket and document; no key's rows meet in one task.

    Rows of a key are spread over buckets by a hash of the document; counts of (key, bucket), few in number,
    give each bucket its first rank.
    """
    spark = pieces.sparkSession
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8) * 4
    spread = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "ids_crc32"), F.lit(buckets)).cast("int"))
    counts = spread.groupBy(key, "bucket").count()
    before = Window.partitionBy(key).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    firsts = counts.select(F.col(key).alias("_key"), F.col("bucket").alias("_bucket"), F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    inner = Window.partitionBy(key, "bucket").orderBy("doc_id", "ids_crc32", "start")
    numbered = spread.withColumn("within", F.row_number().over(inner) - 1)
    joined = numbered.join(firsts, (F.col(key) == F.col("_key")) & (F.col("bucket") == F.col("_bucket")))
    return joined.withColumn("rank", F.col("within") + F.col("first")).drop("_key", "_bucket", "bucket", "within", "first")


def pack(docs: DataFrame, *, tokenizer: str | None = None, capacity: int = CAPACITY, unit: int = UNIT, end_id: int = END_ID) -> DataFrame:
    """Every piece with its sequence and offset."""
    spark = docs.sparkSession
    pieces = written(cut_pieces(docs, tokenizer=tokenizer or tokenizer_path(), capacity=capacity, unit=unit, end_id=end_id), "pieces")
    histogram = {int(r["length"]): int(r["count"]) for r in pieces.groupBy("length").count().collect()}  # at most capacity / unit + unit rows
    whole = histogram.pop(capacity, 0)
    runs = plan_patterns({k // unit: v for k, v in histogram.items() if k >= unit}, capacity // unit)
    table = [(capacity, 0, whole, 1, 0, 0)] if whole else []
    table += [(size, first, ranks, per, sequence + whole, offset) for size, first, ranks, per, sequence, offset in pattern_table(runs, unit)]
    base = whole + sum(times for times, _ in runs)
    plan = spark.createDataFrame(table, "size long, first_rank long, ranks long, per_sequence long, first_sequence long, first_offset long")
    placed = ranked(pieces, "length")
    out = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    within = F.col("rank") - F.col("first_rank")
    stems = (
        placed.where(F.col("length") >= unit)
        .join(F.broadcast(plan), (F.col("length") == F.col("size")) & (F.col("rank") >= F.col("first_rank")) & (F.col("rank") < F.col("first_rank") + F.col("ranks")))
        .withColumn("sequence_id", F.col("first_sequence") + F.expr("(rank - first_rank) div per_sequence"))
        .withColumn("offset", F.col("first_offset") + F.pmod(within, F.col("per_sequence")) * F.col("length"))
    )
    # Tails follow one another, longest first; their places in the stream follow from their ranks alone.
    begin, tails = 0, []
    for length in sorted((k for k in histogram if k < unit), reverse=True):
        tails.append((length, begin))
        begin += length * histogram[length]
    full = begin // capacity
    borders, rest = [full * capacity], begin % capacity
    while rest:
        borders.append(borders[-1] + (1 << (rest.bit_length() - 1)))
        rest -= 1 << (rest.bit_length() - 1)
    stream = spark.createDataFrame(tails, "size long, stream_start long")
    edges = F.array(*[F.lit(b).cast("long") for b in borders])
    holder = lambda at: F.when(at < full * capacity, F.floor(at / capacity)).otherwise(F.lit(full - 1) + F.size(F.filter(edges, lambda b: b <= at)))
    edge = lambda at: F.when(at <= full, at * capacity).otherwise(F.get(edges, (at - full).cast("int")))
    lined = (
        placed.where(F.col("length") < unit)
        .join(F.broadcast(stream), F.col("length") == F.col("size"))
        .withColumn("place", F.col("stream_start") + F.col("rank") * F.col("length"))
        .withColumn("holder", F.explode(F.sequence(holder(F.col("place")).cast("long"), holder(F.col("place") + F.col("length") - 1).cast("long"))))
        .withColumn("from", F.greatest("place", edge(F.col("holder"))))
        .withColumn("to", F.least(F.col("place") + F.col("length"), edge(F.col("holder") + 1)))
    )
    cut_ids = F.col("tail_ids").substr(((F.col("from") - F.col("place")) * 4 + 1).cast("int"), ((F.col("to") - F.col("from")) * 4).cast("int"))
    tail = lined.select(
        "doc_id",
        (F.col("start") + F.col("from") - F.col("place")).alias("start"),
        (F.col("to") - F.col("from")).alias("length"),
        F.crc32(cut_ids).alias("ids_crc32"),
        "doc_tokens",
        (F.col("holder") + base).alias("sequence_id"),
        (F.col("from") - edge(F.col("holder"))).alias("offset"),
    )
    return stems.select(*out).unionByName(tail)
