"""Substring dedup by fixed-block anchors.

Every window of `window` words that also starts in a document of smaller doc_id marks its words for removal.
Each document's words are cut into non-overlapping blocks of `block` words: the reference index. Rolling
windows of `block` words probe the index. A repeat of `window` words holds `runs` = (window + 1) // block - 1
whole blocks of its first document one after another, whatever their phase, so it is enough that rolling
windows probe from the first `block` of every `block * runs` places: one block of the run is met at each
phase. Index entries and probes are one packed shuffle (see `repeats`).

Where the words around a hit, as far as a window can reach, are equal to those of a smaller document, the
hit is settled by their hash. Around other hits the documents' windows are extended one by one: their hashes
meet in buckets, and a window whose sequence has a smaller document is removed. Overlapping removed windows
merge into maximal exact repeats.

Defined cases: words are separated by space and the control characters tab to carriage return and are
compared unchanged; a null text has no words; documents shorter than a window lose nothing; texts of any
length are treated whole; repeats within one document stay; repeated rows count as one document, each
row getting its result; rows that share a doc_id but not their text are documents of their own, in the order of their
texts' SHA-256; a row without doc_id neither gives nor loses words; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, mix64, release_memory, row_bounds, span_hashes, text_buffer, text_or_empty, word_spans, written
from .repeats import COVER, MARK, WANTED, Anchors, Stretches, buckets_of, given_ids, one_text_each, read_spans, read_wanted, runs, shared_marks, span_marks, with_marks, pack_columns, unpack_columns

WINDOW, BLOCK = 50, 7


def block_places(sizes: np.ndarray, window: int = WINDOW, block: int = BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of the index entries and probes of rows with so many words."""
    count = (window + 1) // block - 1
    stripe = block * count
    rows, places = [], []
    per_cycle = np.unique(np.concatenate([np.arange(0, stripe, block), np.arange(block)]))
    usable = np.where(sizes >= window, sizes - block + 1, 0)
    cycles = -(-usable // stripe)
    row = np.repeat(np.arange(len(sizes)), cycles)
    cycle = np.arange(int(cycles.sum())) - np.repeat(np.cumsum(cycles) - cycles, cycles)
    rows = np.repeat(row, len(per_cycle))
    places = (cycle[:, None] * stripe + per_cycle).ravel()
    inside = places < usable[rows]
    return rows[inside], places[inside]


def _words(part: pa.RecordBatch) -> tuple[Stretches, np.ndarray, np.ndarray]:
    """Word hashes' prefix sums, bounds of each row's words, and the document ids."""
    data, offsets = text_buffer(part.column(1))
    starts, ends, row = word_spans(data, offsets)
    return Stretches(span_hashes(data, starts, ends)), row_bounds(row, part.num_rows), part.column(0).to_numpy(zero_copy_only=False)


def word_anchors(part: pa.RecordBatch, window: int = WINDOW, block: int = BLOCK) -> Anchors:
    stretches, bounds, ids = _words(part)
    row, place = block_places(np.diff(bounds), window, block)
    pos = bounds[row] + place
    left = np.minimum(place, window - block)
    right = np.minimum(bounds[row + 1] - pos, window)
    c = mix64(stretches.hash(pos - left, pos + right) ^ (left.astype(np.uint64) << np.uint64(8)))
    return Anchors(stretches.hash(pos, pos + block), c, ids[row].astype(np.int64), place, left.astype(np.uint8), right.astype(np.uint8))


def _extend(window: int, block: int, buckets: int):
    """Hashes of the windows over the wanted anchors that no settled stretch covers, packed by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def flush() -> pa.RecordBatch:
            code, doc, at = (np.concatenate([x[k] for x in held]) for k in range(3))
            order = np.lexsort((doc, code))
            code, doc, at = code[order], doc[order], at[order]
            edges = np.searchsorted(code // np.uint64(-(-(1 << 64) // buckets)), np.arange(buckets + 1, dtype=np.uint64))
            rows = [(k, pack_columns([code[a:b], doc[a:b], at[a:b].astype(np.uint32)])) for k, (a, b) in enumerate(zip(edges, edges[1:])) if b > a]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.binary()), strict=True)], ["bucket", "packed"])

        for part in chunks(batches):
            stretches, bounds, ids = _words(part)
            for k, (wanted, settled) in enumerate(zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True)):
                pos = read_wanted(wanted or [])[0]
                size = bounds[k + 1] - bounds[k]
                if not len(pos) or size < window:
                    continue
                need = np.zeros(size + 2, np.int64)
                np.add.at(need, np.maximum(pos - (window - block), 0), 1)
                np.add.at(need, pos + 1, -1)
                start = np.flatnonzero(np.cumsum(need[: size - window + 1]) > 0)
                opens, closes = read_spans(settled or [])
                inside = np.searchsorted(opens, start, "right") - 1
                if len(opens):
                    start = start[(inside < 0) | (start + window > closes[np.maximum(inside, 0)])]
                held.append((stretches.hash(bounds[k] + start, bounds[k] + start + window), np.full(len(start), ids[k], np.int64), start))
            if sum(len(x[0]) for x in held) > 500_000:
                yield flush()
                held = []
        if held and sum(len(x[0]) for x in held):
            yield flush()

    return run


def _first_documents(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs: dict[int, list[bytes]] = {}
        for batch in batches:
            for bucket, packed in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                blobs.setdefault(bucket, []).append(packed)
        for bucket in sorted(blobs):
            code, doc, at = (np.concatenate(c) for c in zip(*(unpack_columns(b, [np.uint64, np.int64, np.uint32]) for b in blobs.pop(bucket)), strict=True))
            order = np.argsort(code, kind="stable")
            code, doc, at = code[order], doc[order], at[order].astype(np.int64)
            first, stop = runs(code)
            later = doc > np.repeat(np.minimum.reduceat(doc, first), stop - first)
            rows = list(span_marks(doc[later], at[later], at[later] + window))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.binary()), strict=True)], ["doc_id", "kind", "packed"])
        release_memory()

    return run


def word_repeats(docs: DataFrame, *, window: int = WINDOW, block: int = BLOCK) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and the removed stretches of words of every row."""
    own, numbers = one_text_each(docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")))
    named = own.where("doc_id IS NOT NULL")
    marks = shared_marks(named, lambda part: word_anchors(part, window, block), within=False, name="word-marks")
    buckets = buckets_of(docs)
    wanting = marks.where(F.col("kind") == WANTED).select(F.col("doc_id").alias("_of")).distinct()
    asked = marks.join(wanting, F.col("doc_id") == F.col("_of"), "left_semi")
    around = with_marks(named, asked, [WANTED, COVER], "inner").mapInArrow(_extend(window, block, buckets), "bucket int, packed binary")
    seen = written(around.repartitionById(buckets, "bucket").mapInArrow(_first_documents(window), MARK), "word-spans")
    every = marks.where(F.col("kind") == COVER).unionByName(seen)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            data, offsets = text_buffer(part.column(1))
            raw, rows = data.tobytes(), []
            for k, blobs in enumerate(part.column(2).to_pylist()):
                words = raw[offsets[k] : offsets[k + 1]].split()
                start, stop = read_spans(blobs or [])
                edges = [0, *(x for pair in zip(start.tolist(), stop.tolist(), strict=True) for x in pair), len(words)]
                kept = [w for a, b in zip(edges[::2], edges[1::2], strict=True) for w in words[a:b]]
                rows.append((len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest(), [{"start": a, "stop": b} for a, b in zip(start.tolist(), stop.tolist(), strict=True)]))
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())])))
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True))], ["doc_id", "n_words", "n_removed", "kept_sha256", "spans"])

    done = with_marks(own, every, [COVER], "left").mapInArrow(finish, "doc_id long, n_words long, n_removed long, kept_sha256 string, spans array<struct<start: long, stop: long>>")
    return given_ids(done, numbers)
