"""Exact repeats across a corpus, found from anchors whose choice depends on the text alone or covers every phase.

The parts that the byte-level and the word-level operators share. A text is a sequence of symbols, with
prefix sums that give a 64-bit hash of any stretch of it. Anchors are chosen so that two equal windows share
an anchor at one offset. A task sorts the anchors of many documents, settles those whose whole surroundings
it has seen before, and ships the first of each kind, packed by bucket of the anchor's hash: a passage that
a third of all documents hold costs one record for each anchor and task, whatever the number of documents.
Buckets settle what equal surroundings tell and ask for the texts around the other shared anchors only.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.tensor import dictionary
from .common import chunks, mix64, release_memory, text_or_empty, unused, written

#: Kinds of marks on a document: stretches found to be repeats, and anchors whose surroundings are wanted.
COVER, WANTED = 1, 2
MARK = "doc_id long, kind int, packed binary"
#: Anchors that a task gathers before it packs them; bounds its memory.
GATHER = 400_000
_RADIX = np.uint64(0xD6E8FEB86659FD93)
_INVERSE = np.uint64(pow(int(_RADIX), -1, 1 << 64))


def _cumulative(radix: np.uint64, count: int) -> np.ndarray:
    return np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(max(count - 1, 0), radix, np.uint64))])[:count]


_TABLES: dict[str, np.ndarray] = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


def _powers(count: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_TABLES["up"]) < count:
        size = max(count, 2 * len(_TABLES["up"]))
        _TABLES["up"], _TABLES["down"] = _cumulative(_RADIX, size), _cumulative(_INVERSE, size)
    return _TABLES["up"], _TABLES["down"]


class Stretches:
    """Hashes of any stretches of a sequence of 64-bit symbol codes."""

    def __init__(self, codes: np.ndarray) -> None:
        up, self.down = _powers(len(codes) + 1)
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(codes * up[: len(codes)], dtype=np.uint64)])

    def hash(self, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        value = (self.sums[stop] - self.sums[start]) * self.down[start]
        return mix64(value ^ ((stop - start).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))


@dataclass
class Anchors:
    """Anchors of documents: hash, hash of the surroundings, document, place, and how far the surroundings reach."""

    h: np.ndarray
    c: np.ndarray
    doc: np.ndarray
    pos: np.ndarray
    left: np.ndarray
    right: np.ndarray

    def take(self, which: np.ndarray) -> Anchors:
        return Anchors(*(getattr(self, f)[which] for f in FIELDS))


FIELDS = {"h": np.uint64, "c": np.uint64, "doc": np.int64, "pos": np.int64, "left": np.uint8, "right": np.uint8}


def joined(parts: list[Anchors]) -> Anchors:
    return Anchors(*(np.concatenate([getattr(p, f) for p in parts] or [np.zeros(0, t)]).astype(t) for f, t in FIELDS.items()))


def _planes(values: np.ndarray) -> bytes:
    """Bytes of an integer column, highest first, each in a plane of its own: sorted and small values compress."""
    return values.astype(values.dtype.newbyteorder(">")).view(np.uint8).reshape(len(values), -1).T.tobytes()


def pack_columns(columns: list[np.ndarray]) -> bytes:
    return len(columns[0]).to_bytes(4, "big") + zstandard.compress(b"".join(map(_planes, columns)), 1)


def unpack_columns(blob: bytes, kinds: list) -> list[np.ndarray]:
    n, raw, at, out = int.from_bytes(blob[:4], "big"), zstandard.decompress(blob[4:]), 0, []
    for kind in map(np.dtype, kinds):
        plane = np.frombuffer(raw, np.uint8, n * kind.itemsize, at).reshape(kind.itemsize, n)
        out.append(np.ascontiguousarray(plane.T).view(kind.newbyteorder(">")).ravel().astype(kind))
        at += n * kind.itemsize
    return out


def pack_anchors(anchors: Anchors) -> bytes:
    """Anchors sorted by hash, with documents as numbers into a table of their own."""
    docs, number = np.unique(anchors.doc, return_inverse=True)
    table = pack_columns([docs])
    columns = [anchors.h, anchors.c, number.astype(np.uint32), anchors.pos.astype(np.uint32), anchors.left, anchors.right]
    return len(table).to_bytes(4, "big") + table + pack_columns(columns)


def unpack_anchors(blob: bytes) -> Anchors:
    size = int.from_bytes(blob[:4], "big")
    (docs,) = unpack_columns(blob[4 : 4 + size], [np.int64])
    h, c, number, pos, left, right = unpack_columns(blob[4 + size :], [np.uint64, np.uint64, np.uint32, np.uint32, np.uint8, np.uint8])
    return Anchors(h, c, docs[number], pos.astype(np.int64), left, right)


def merge_spans(doc: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Union of stretches within each document, in order."""
    if not len(doc):
        return doc, start, stop
    order = np.lexsort((start, doc))
    doc, start, stop = doc[order], start[order], stop[order]
    _, number = np.unique(doc, return_inverse=True)
    base = number * (int(stop.max()) + 2)
    reach = np.maximum.accumulate(base + stop)
    opens = np.concatenate([[True], (base + start)[1:] > reach[:-1]])
    first = np.flatnonzero(opens)
    last = np.append(first[1:], len(doc)) - 1
    return doc[first], start[first], reach[last] - base[last]


def runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and stops of the runs of equal values."""
    if not len(values):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]]))
    return first, np.append(first[1:], len(values))


def span_marks(doc: np.ndarray, start: np.ndarray, stop: np.ndarray) -> Iterator[tuple[int, int, bytes]]:
    doc, start, stop = merge_spans(doc, start, stop)
    for a, b in zip(*runs(doc), strict=True):
        yield int(doc[a]), COVER, np.concatenate([start[a:b], stop[a:b]]).astype("<u4").tobytes()


def read_spans(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    starts, stops = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for blob in blobs:
        half = np.frombuffer(blob, "<u4").astype(np.int64).reshape(2, -1)
        starts.append(half[0])
        stops.append(half[1])
    start, stop = np.concatenate(starts), np.concatenate(stops)
    _, start, stop = merge_spans(np.zeros(len(start), np.int64), start, stop)
    return start, stop


def settle(anchors: Anchors, *, within: bool) -> tuple[Anchors, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The first anchors of each kind of surroundings, and the stretches around later ones, which are repeats.

    Later means a larger (document, place) if `within` a document counts, else a larger document. An anchor that
    is given twice, as by repeated rows, counts once: it is not later than itself.
    """
    order = np.lexsort((anchors.pos, anchors.doc, anchors.c, anchors.h))
    a = anchors.take(order)
    fresh = np.ones(len(a.h), bool)
    fresh[1:] = (a.h[1:] != a.h[:-1]) | (a.c[1:] != a.c[:-1])
    again = np.zeros(len(a.h), bool)
    again[1:] = ~fresh[1:] & (a.doc[1:] == a.doc[:-1]) & (a.pos[1:] == a.pos[:-1])
    if again.any():
        a, fresh = a.take(np.flatnonzero(~again)), fresh[~again]
    if within:
        later = ~fresh
    else:
        head = np.flatnonzero(fresh)
        lowest = np.repeat(a.doc[head], np.diff(np.append(head, len(a.h))))
        later = a.doc > lowest
    gone = a.take(np.flatnonzero(later))
    return a.take(np.flatnonzero(~later)), (gone.doc, gone.pos - gone.left, gone.pos + gone.right)


def one_text_each(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """`docs` with one text for each doc_id, and (given doc_id, SHA-256, number) of each text where that took new numbers.

    Rows that share a doc_id but not their text are documents of their own, in the order of their texts' SHA-256.
    Only where there are such rows are the documents numbered anew, in the order of (doc_id, SHA-256).
    """
    text = text_or_empty()
    named = docs.where("doc_id IS NOT NULL")
    code = F.xxhash64(text)
    clashes = named.groupBy("doc_id").agg(F.min(code).alias("low"), F.max(code).alias("high")).where("low <> high")
    if clashes.count() == 0:
        return docs, None
    sha = F.sha2(text.cast("binary"), 256)
    entries = dictionary(named.select(F.struct(F.col("doc_id").alias("given"), sha.alias("sha")).alias("k1")), 1)
    given, digest, number = (unused(docs, name) for name in ("_given", "_sha", "_number"))
    numbers = entries.select(F.col("key.given").alias(given), F.col("key.sha").alias(digest), F.col("idx").alias(number))
    own = docs.join(numbers, (F.col("doc_id") == F.col(given)) & (sha == F.col(digest)), "left")
    return own.select(*(F.col(number).alias(c) if c == "doc_id" else F.col(f"`{c}`") for c in docs.columns)), numbers


def given_ids(found: DataFrame, numbers: DataFrame | None) -> DataFrame:
    """`found` with the doc_ids that were given, where `one_text_each` took others."""
    if numbers is None:
        return found
    given, digest, number = numbers.columns
    back = found.join(numbers.drop(digest), F.col("doc_id") == F.col(number), "left")
    return back.select(*(F.col(given).alias(c) if c == "doc_id" else F.col(f"`{c}`") for c in found.columns))


def buckets_of(docs: DataFrame) -> int:
    return max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 8) * 2


def shared_marks(docs: DataFrame, find: Callable[[pa.RecordBatch], Anchors], *, within: bool, name: str) -> DataFrame:
    """Marks (MARK) from anchors and their surroundings, in one shuffle of packed anchors."""
    buckets = buckets_of(docs)
    names = ["bucket", "doc_id", "kind", "packed"]

    def emit(rows: list[tuple]) -> pa.RecordBatch:
        columns = list(zip(*rows, strict=True)) if rows else [(), (), (), ()]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int32(), pa.int64(), pa.int32(), pa.binary()), strict=True)], names)

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def flush() -> pa.RecordBatch:
            first, spans = settle(joined(held), within=within)
            rows = [(int(doc % buckets), doc, kind, packed) for doc, kind, packed in span_marks(*spans)]
            bucket = first.h // np.uint64(-(-(1 << 64) // buckets))
            edges = np.searchsorted(bucket, np.arange(buckets + 1, dtype=np.uint64))
            rows += [(k, None, 0, pack_anchors(first.take(np.arange(edges[k], edges[k + 1])))) for k in range(buckets) if edges[k + 1] > edges[k]]
            return emit(rows)

        held: list[Anchors] = []
        for part in chunks(batches):
            held.append(find(part))
            if sum(len(x.h) for x in held) > GATHER:
                yield flush()
                held = []
        if held:
            yield flush()

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs: dict[int, list[bytes]] = {}
        for batch in batches:
            for bucket, doc, kind, packed in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind:
                    yield pa.RecordBatch.from_arrays([pa.array([doc], pa.int64()), pa.array([kind], pa.int32()), pa.array([packed], pa.binary())], names[1:])
                else:
                    blobs.setdefault(bucket, []).append(packed)
        for bucket in sorted(blobs):
            a = joined([unpack_anchors(b) for b in blobs.pop(bucket)])
            order = np.argsort(a.h, kind="stable")
            sorted_h = a.h[order]
            twin = np.zeros(len(sorted_h), bool)
            twin[1:] = sorted_h[1:] == sorted_h[:-1]
            twin[:-1] |= twin[1:]
            first, spans = settle(a.take(order[twin]), within=within)
            rows = list(span_marks(*spans))
            # Anchors left with other surroundings under one hash: what their texts share must be seen.
            edge, stop = runs(first.h)
            size = stop - edge
            low, high = (np.minimum.reduceat(first.c, edge), np.maximum.reduceat(first.c, edge)) if len(edge) else (first.c, first.c)
            several = low != high
            if not within and len(edge):
                several &= np.minimum.reduceat(first.doc, edge) != np.maximum.reduceat(first.doc, edge)
            want = first.take(np.flatnonzero(np.repeat(several, size)))
            by_doc = np.lexsort((want.pos, want.doc))
            doc, pos, h, left, right = (getattr(want, f)[by_doc] for f in ("doc", "pos", "h", "left", "right"))
            for x, y in zip(*runs(doc), strict=True):
                rows.append((int(doc[x]), WANTED, b"".join((pos[x:y].astype("<u4").tobytes(), h[x:y].astype("<u8").tobytes(), left[x:y].tobytes(), right[x:y].tobytes()))))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.binary()), strict=True)], names[1:])
        release_memory()

    packed = docs.mapInArrow(gather, "bucket int, doc_id long, kind int, packed binary")
    return written(packed.repartitionById(buckets, "bucket").mapInArrow(judge, MARK), name)


def read_wanted(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Places, hashes and reaches to the left and right of the wanted anchors of a document."""
    parts = [(np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64))]
    for blob in blobs:
        n = len(blob) // 14
        pos, h = np.frombuffer(blob, "<u4", n), np.frombuffer(blob, "<u8", n, 4 * n)
        left, right = np.frombuffer(blob, np.uint8, n, 12 * n), np.frombuffer(blob, np.uint8, n, 13 * n)
        parts.append((pos.astype(np.int64), h.astype(np.uint64), left.astype(np.int64), right.astype(np.int64)))
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True))


def with_marks(docs: DataFrame, marks: DataFrame, kinds: list[int], how: str) -> DataFrame:
    """doc_id, text and the packed marks of the given kinds; a document's marks are bounded by its own length."""
    at = unused(docs, "_at")
    chosen = marks.where(F.col("kind").isin(kinds)).groupBy(F.col("doc_id").alias(at)).agg(*(F.collect_list(F.when(F.col("kind") == k, F.col("packed"))).alias(unused(docs, f"marks_{k}")) for k in kinds))
    return docs.join(chosen, F.col("doc_id") == F.col(at), how).drop(at)
