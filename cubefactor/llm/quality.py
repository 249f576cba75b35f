"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics are computed in Arrow batches; the trees are fitted on the driver from a bounded sample of
labelled rows (`max_train_rows`), flattened into arrays and walked with vectorised numpy on the executors.

Defined cases: a null text counts as empty and gets a score; an empty table gives no rows; with no usable
label every score is 0.5; with labels of one class the score is that class's smoothed share; a null doc_id
is kept, is never used for learning and is not held out; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, crc_fold, row_bounds, span_hashes, text_buffer, text_or_empty, word_spans

#: Byte classes whose shares are statistics (fixed values).
BYTE_CLASSES = {
    "lower": range(0x61, 0x7B),
    "upper": range(0x41, 0x5B),
    "digit": range(0x30, 0x3A),
    "blank": (0x20, 0x09),
    "newline": (0x0A, 0x0D),
    "stop": b".,;:?",
    "bang": b"!",
    "quote": b"'\"()-",
    "mark": b"#$%&*+/<=>@[\\]^_`{|}~",
    "control": [*range(0, 9), 0x0B, 0x0C, *range(0x0E, 0x20), 0x7F],
    "wide": range(0x80, 0x100),
}
_CLASS_OF = np.zeros(256, np.int64)
for _number, _bytes in enumerate(BYTE_CLASSES.values()):
    _CLASS_OF[list(_bytes)] = _number

STATISTICS = [
    *(f"share_{name}" for name in BYTE_CLASSES),
    "log_bytes", "byte_entropy", "log_words", "word_bytes", "longest_word", "distinct_words", "top_word", "echo_words",
    "distinct_pairs", "shouted_words", "marked_words", "lines", "line_bytes", "distinct_lines", "closed_lines", "short_words",
]


def _per_row(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.float64)])
    return total[bounds[1:]] - total[bounds[:-1]]


def _distinct(row: np.ndarray, codes: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct codes of each row, and the count of its most frequent one."""
    distinct, top = np.zeros(rows), np.zeros(rows)
    if len(row):
        keys = np.sort((row.astype(np.uint64) << np.uint64(40)) | (codes >> np.uint64(24)))
        first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
        of = (keys[first] >> np.uint64(40)).astype(np.int64)
        distinct = np.bincount(of, minlength=rows).astype(float)
        np.maximum.at(top, of, np.diff(np.append(first, len(keys))))
    return distinct, top


def statistics(array: pa.Array) -> np.ndarray:
    """One row of STATISTICS for each text of the array."""
    data, offsets = text_buffer(array)
    rows = len(offsets) - 1
    sizes = np.diff(offsets).astype(float)
    safe = np.maximum(sizes, 1)
    out = np.zeros((rows, len(STATISTICS)))
    row_of = np.repeat(np.arange(rows), np.diff(offsets))
    counts = np.bincount(row_of * 256 + data, minlength=rows * 256).reshape(rows, 256)
    for number in range(len(BYTE_CLASSES)):
        out[:, number] = counts[:, _CLASS_OF == number].sum(1) / safe
    shares = counts / safe[:, None]
    entropy = -(shares * np.log2(np.where(shares > 0, shares, 1))).sum(1)
    starts, ends, row = word_spans(data, offsets)
    codes, bounds = span_hashes(data, starts, ends), row_bounds(row, rows)
    words = np.diff(bounds).astype(float)
    lengths = (ends - starts).astype(float)
    longest = np.zeros(rows)
    np.maximum.at(longest, row, lengths)
    distinct, top = _distinct(row, codes, rows)
    same_row = row[1:] == row[:-1]
    echoes = np.concatenate([[False], same_row & (codes[1:] == codes[:-1])]) if len(row) else np.zeros(0, bool)
    pairs, _ = _distinct(row[1:][same_row], (codes[1:] * np.uint64(3) ^ codes[:-1])[same_row], rows) if len(row) else (np.zeros(rows), None)
    is_upper = np.concatenate([[0], np.cumsum((_CLASS_OF[data] == 1) & True)])
    is_lower = np.concatenate([[0], np.cumsum(_CLASS_OF[data] == 0)])
    shouted = (is_upper[ends] - is_upper[starts] > 1) & (is_lower[ends] == is_lower[starts]) if len(row) else np.zeros(0, bool)
    marked = np.isin(data[ends - 1], list(b"#$%&*|!")) if len(row) else np.zeros(0, bool)
    breaks = np.flatnonzero(data == 0x0A)
    line_starts = np.sort(np.concatenate([offsets[:-1][sizes > 0], breaks + 1]))
    line_starts = line_starts[line_starts < len(data)] if len(data) else line_starts[:0]
    line_starts = np.unique(line_starts)
    line_ends = np.append(line_starts[1:], len(data))
    line_row = np.searchsorted(offsets, line_starts, "right") - 1
    lines = np.bincount(line_row, minlength=rows).astype(float) if len(line_row) else np.zeros(rows)
    own_lines, _ = _distinct(line_row, span_hashes(data, line_starts, line_ends), rows)
    last = line_ends - 1 - (data[line_ends - 1] == 0x0A) if len(line_row) else line_ends
    closed = np.bincount(line_row, weights=np.isin(data[np.maximum(last, 0)], list(b".!?")), minlength=rows) if len(line_row) else np.zeros(rows)
    some, some_lines = np.maximum(words, 1), np.maximum(lines, 1)
    out[:, len(BYTE_CLASSES) :] = np.column_stack([
        np.log1p(sizes), entropy, np.log1p(words), _per_row(lengths, bounds) / some, longest, distinct / some, top / some,
        _per_row(echoes, bounds) / some, pairs / some, _per_row(shouted, bounds) / some, _per_row(marked, bounds) / some,
        lines, sizes / some_lines, own_lines / some_lines, closed / some_lines, _per_row(lengths <= 3, bounds) / some,
    ])
    return out


@dataclass
class FlatTrees:
    """All trees in five arrays; a leaf points at itself, so every walk takes `depth` steps."""

    roots: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    base: float
    depth: int

    def margin(self, table: np.ndarray) -> np.ndarray:
        node = np.broadcast_to(self.roots, (len(table), len(self.roots)))
        at = np.arange(len(table))[:, None]
        for _ in range(self.depth if len(self.roots) else 0):
            goes_left = table[at, self.feature[node]] <= self.threshold[node]
            node = np.where(goes_left, self.left[node], self.right[node])
        return self.base + (self.value[node].sum(1) if len(self.roots) else np.zeros(len(table)))

    def score(self, table: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(table), -40, 40)))


def fit_trees(table: np.ndarray, label: np.ndarray, *, trees: int = 60, depth: int = 4, bins: int = 64, rate: float = 0.15, ridge: float = 1.0, least: float = 5.0) -> FlatTrees:
    """Second-order boosting of the logistic loss; splits are searched over per-feature histograms."""
    n, width = table.shape
    share = (label.sum() + 1) / (n + 2) if n else 0.5
    base = float(np.log(share / (1 - share)))
    cuts = [np.unique(np.quantile(table[:, f], np.linspace(0, 1, bins + 1)[1:-1])) if n else np.zeros(0) for f in range(width)]
    coded = np.column_stack([np.searchsorted(cuts[f], table[:, f], "left") for f in range(width)]) if n else np.zeros((0, width), int)
    arrays: dict[str, list] = {k: [] for k in ("feature", "threshold", "left", "right", "value")}

    def leaf(value: float) -> int:
        number = len(arrays["value"])
        for key, entry in (("feature", 0), ("threshold", np.inf), ("left", number), ("right", number), ("value", value)):
            arrays[key].append(entry)
        return number

    roots, margin = [], np.full(n, base)
    offsets = np.arange(width) * bins
    for _ in range(trees if n and 0 < label.sum() < n else 0):
        chance = 1 / (1 + np.exp(-margin))
        slope, curve = label - chance, chance * (1 - chance)
        roots.append(leaf(0.0))
        open_nodes = [(roots[-1], np.arange(n))]
        for level in range(depth + 1):
            following = []
            for number, members in open_nodes:
                g, h = slope[members].sum(), curve[members].sum()
                best = (1e-6, None, None)
                if level < depth and len(members) >= 2 * least:
                    codes = (coded[members] + offsets).ravel()
                    gains_g = np.bincount(codes, np.repeat(slope[members], width), width * bins).reshape(width, bins).cumsum(1)
                    gains_h = np.bincount(codes, np.repeat(curve[members], width), width * bins).reshape(width, bins).cumsum(1)
                    rows = np.bincount(codes, minlength=width * bins).reshape(width, bins).cumsum(1)
                    gain = gains_g**2 / (gains_h + ridge) + (g - gains_g) ** 2 / (h - gains_h + ridge) - g * g / (h + ridge)
                    gain[(rows < least) | (len(members) - rows < least)] = -1
                    f, b = np.unravel_index(int(gain.argmax()), gain.shape)
                    if gain[f, b] > best[0] and b < len(cuts[f]):
                        best = (float(gain[f, b]), int(f), int(b))
                if best[1] is None:
                    arrays["value"][number] = float(rate * g / (h + ridge))
                    margin[members] += arrays["value"][number]
                    continue
                _, f, b = best
                goes_left = coded[members, f] <= b
                arrays["feature"][number], arrays["threshold"][number] = f, float(cuts[f][b])
                arrays["left"][number], arrays["right"][number] = leaf(0.0), leaf(0.0)
                following += [(arrays["left"][number], members[goes_left]), (arrays["right"][number], members[~goes_left])]
            open_nodes = following
    return FlatTrees(np.array(roots, np.int64), np.array(arrays["feature"], np.int64), np.array(arrays["threshold"], float), np.array(arrays["left"], np.int64), np.array(arrays["right"], np.int64), np.array(arrays["value"], float), base, depth)


def labelled_sample(docs: DataFrame, labels: DataFrame, target: str, learn: "F.Column", max_rows: int) -> DataFrame:
    """At most `max_rows` labelled documents (id, text, label), those of the smallest hashes, so that the choice is stable."""
    chosen = (
        labels.select(F.col("doc_id"), F.col(target).cast("int").alias("label"))
        .where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1) & learn)
        .orderBy(F.xxhash64("doc_id"), "doc_id", "label")
        .limit(max_rows)
    )
    return docs.select("doc_id", text_or_empty().alias("text")).join(F.broadcast(chosen), "doc_id")


def fit_quality(docs: DataFrame, labels: DataFrame, *, target: str = "quality", fold: int = 5, held: int = 0, max_train_rows: int = 20_000, **growth) -> FlatTrees:
    """Fit on labelled rows outside the held-out fold; at most `max_train_rows` rows reach the driver."""
    sample = labelled_sample(docs, labels, target, crc_fold(F.col("doc_id"), fold) != held, max_train_rows)

    def tabulate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            table = statistics(part.column(0))
            yield pa.RecordBatch.from_arrays([part.column(1), pa.array(list(table), pa.list_(pa.float64()))], ["label", "x"])

    got = sample.select("text", "label").mapInArrow(tabulate, "label int, x array<double>").toArrow()
    table = np.stack(got.column("x").to_numpy()) if got.num_rows else np.zeros((0, len(STATISTICS)))
    label = got.column("label").to_numpy().astype(float)
    order = np.lexsort([*table.T[::-1], label]) if got.num_rows else np.zeros(0, int)  # the same trees whatever order rows arrive in
    return fit_trees(table[order], label[order], **growth)


def score_quality(docs: DataFrame, model: FlatTrees) -> DataFrame:
    """Columns doc_id and score for every row of `docs`."""

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(model.score(statistics(part.column(1))))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(score, "doc_id long, score double")


def classify_quality(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.3, fold: int = 5, held: int = 0, **options) -> DataFrame:
    """doc_id, held_out, score and predicted for every document."""
    scored = score_quality(docs, fit_quality(docs, labels, fold=fold, held=held, **options))
    return scored.select(
        "doc_id",
        F.coalesce(crc_fold(F.col("doc_id"), fold) == held, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= threshold).cast("int").alias("predicted"),
    )


def keep_quality(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.3, **options) -> DataFrame:
    """The rows of `docs`, all columns, whose score reaches the threshold; documents are never changed."""
    model = fit_quality(docs, labels, **options)
    fields = docs.columns

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            keep = model.score(statistics(part.column(part.schema.get_field_index("text")))) >= threshold
            yield part.filter(pa.array(keep))

    return docs.mapInArrow(decide, docs.schema).select(*fields)
