"""Suffix-array dedup: maximal byte repeats from the interval tree of an enhanced suffix array.

Every byte string of `window` bytes that starts again later marks its later bytes for removal. A suffix
array of the whole corpus in one place is out of reach, so suffixes meet in buckets: each window's anchor is
the least hashed gram in it (leftmost on ties), which equal windows share at one offset. Anchors whose whole
surroundings were seen before are settled by their hash (see `repeats`); around the other shared anchors the
bytes are fetched, and each bucket builds an enhanced suffix array over them: suffixes grouped by their first
`window` bytes and sorted, with the common prefix of neighbours. A scan with a stack walks the tree of
common-prefix intervals and reports each interval whose occurrences have different bytes on their left, as a
maximal repeat with all its occurrences, not only neighbours. All but the first occurrence are removed.

Defined cases: a null text is empty; texts shorter than the window lose nothing; texts of any length are
treated whole (up to 4 GB each); matches never cross documents; repeated rows count as one document, each row
getting its result, and a place is never later than itself; rows that share a doc_id must share their text; a row without doc_id neither gives nor loses
text; an empty table gives no rows; extra columns are ignored or, in `remove_repeats`, kept.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, mix64, release_memory, text_buffer, text_or_empty, written
from .repeats import COVER, MARK, WANTED, Anchors, Stretches, buckets_of, given_ids, one_text_each, pack_columns, read_spans, read_wanted, runs, shared_marks, span_marks, unpack_columns, with_marks

WINDOW, GRAM = 100, 16
_CODES = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F))


def _eights(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on, as one integer (the last ones are padded with zeros)."""
    padded = np.concatenate([data, np.zeros(16, np.uint8)])
    out = np.zeros(len(data), np.uint64)
    for phase in range(8):
        count = len(out[phase::8])
        out[phase::8] = np.frombuffer(padded[phase:].tobytes()[: 8 * count], "<u8")
    return out


def anchor_places(data: np.ndarray, offsets: np.ndarray, window: int = WINDOW, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Anchors in order, with the start of the first and of the last window that each stands for.

    Every window within a row has one anchor, and the windows of an anchor follow one another.
    """
    n, span = len(data), window - gram + 1
    if n < window:
        return (np.zeros(0, np.int64),) * 3
    eights = _eights(data)
    grams = eights[: n - gram + 1] * np.uint64(0x9E3779B97F4A7C15) + eights[gram - 8 : n - gram + 1 + gram - 8] * np.uint64(0xC2B2AE3D27D4EB4F)
    grams ^= grams >> np.uint64(32)
    grams *= np.uint64(0xFF51AFD7ED558CCD)
    # The high bits decide and the place breaks ties, so that the leftmost of equal grams wins.
    low = np.uint64((1 << 24) - 1)
    least = (grams & ~low) | np.arange(len(grams), dtype=np.uint64)
    width = 1
    while 2 * width <= span:
        least = np.minimum(least[:-width], least[width:])
        width *= 2
    if width < span:
        least = np.minimum(least[: len(least) - (span - width)], least[span - width :])
    sizes = np.diff(offsets)
    whole = sizes >= window
    first = np.repeat(offsets[:-1][whole], sizes[whole] - window + 1)
    within = np.arange(len(first)) - np.repeat(np.cumsum(sizes[whole] - window + 1) - (sizes[whole] - window + 1), sizes[whole] - window + 1)
    start = first + within
    chosen = (least[start] & low).astype(np.int64)
    begin, end = runs(chosen)
    return chosen[begin], start[begin], start[end - 1]


def byte_anchors(part: pa.RecordBatch, window: int = WINDOW, gram: int = GRAM) -> Anchors:
    """Anchors of the rows (doc_id, text) of a batch."""
    data, offsets = text_buffer(part.column(1))
    ids = part.column(0).to_numpy(zero_copy_only=False)
    found = []
    step = 1 << 23  # places must fit the tie-breaking bits; longer texts are read in overlapping stretches
    for a in range(0, max(len(data), 1), step):
        b = min(a + step + window - 1, len(data))
        inner = np.unique(np.clip(offsets, a, b)) - a
        if len(inner) > 1:
            found.append(tuple(x + a for x in anchor_places(data[a:b], inner, window, gram)))
    pos, start, last = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 3
    row = np.searchsorted(offsets, pos, "right") - 1
    left, right = pos - start, last + window - pos
    stretches = Stretches(_CODES[data])
    h, c = stretches.hash(pos, pos + gram), stretches.hash(pos - left, pos + right)
    c = mix64(c ^ (left.astype(np.uint64) << np.uint64(8)))
    return Anchors(h, c, ids[row].astype(np.int64), pos - offsets[row], left.astype(np.uint8), right.astype(np.uint8))


def interval_tree(common: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """(depth, first, last) of every interval of sorted suffixes whose common prefix has `least` symbols or more.

    `common[i]` is the common prefix of suffixes i and i+1. One scan with a stack of open intervals.
    """
    out: list[tuple[int, int, int]] = []
    open_: list[tuple[int, int]] = []
    for i, depth in enumerate([*common, 0]):
        start = i
        while open_ and open_[-1][0] > depth:
            was, start = open_.pop()
            out.append((was, start, i))
        if depth >= least and (not open_ or open_[-1][0] < depth):
            open_.append((depth, start))
    return out


def maximal_repeats(text: np.ndarray, bounds: np.ndarray, least: int = WINDOW) -> Iterator[tuple[int, np.ndarray]]:
    """(length, places of all occurrences) of the repeats of `least` bytes or more among the pieces of `text`.

    Pieces are text[bounds[k]:bounds[k+1]]; repeats stay within pieces. A repeat is reported if its
    occurrences have different bytes before them, or one begins its piece. Occurrences are unordered.
    """
    sizes = np.diff(bounds)
    whole = np.flatnonzero(sizes >= least)
    count = sizes[whole] - least + 1
    place = np.repeat(bounds[whole], count) + np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
    stop = np.repeat(bounds[whole + 1], count)
    if not len(place):
        return
    code = Stretches(_CODES[text]).hash(place, place + least)
    order = np.argsort(code, kind="stable")
    code, place, stop = code[order], place[order], stop[order]
    first = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]]))
    size = np.diff(np.append(first, len(code)))
    before = np.where(np.isin(place, bounds[:-1]), 256 + np.arange(len(place)), text[np.maximum(place - 1, 0)])
    diverse = (size > 1) & (np.minimum.reduceat(before, first) != np.maximum.reduceat(before, first))
    picked = np.flatnonzero(np.repeat(diverse, size))
    place, stop, before, size = place[picked], stop[picked], before[picked], size[diverse]
    depth = int(sizes.max())
    begin = np.cumsum(size) - size
    group = np.repeat(np.arange(len(size)), size)
    block = max(1, (2 << 20) // depth)
    at = 0
    while at < len(size):  # whole groups, about 2 MB of suffixes at a time
        upto = max(at + 1, int(np.searchsorted(begin, begin[at] + block, "right")) - 1)
        a, b = int(begin[at]), int(begin[upto]) if upto < len(size) else len(place)
        reach = place[a:b, None] + np.arange(depth)
        suffix = np.where(reach < stop[a:b, None], text[np.minimum(reach, len(text) - 1)].astype(np.int16) + 1, 0)
        head = (group[a:b] - group[a]).astype(">u4").view(np.uint8).reshape(-1, 4).astype(np.int16)
        key = np.ascontiguousarray(np.hstack([head, suffix]).astype(">u2")).view(f"V{2 * (depth + 4)}").ravel()
        ranked = np.argsort(key.view(f"S{2 * (depth + 4)}"), kind="stable")
        suffix, own = suffix[ranked], group[a:b][ranked]
        differs = (suffix[1:] != suffix[:-1]) | (suffix[1:] == 0)
        common = np.where(differs.any(1), differs.argmax(1), depth)
        common[own[1:] != own[:-1]] = 0
        places, befores = place[a:b][ranked], before[a:b][ranked]
        changes = np.concatenate([[0], np.cumsum(befores[1:] != befores[:-1])])
        tree = np.array(interval_tree(common.tolist(), least), np.int64).reshape(-1, 3)
        for length, x, y in tree[changes[tree[:, 2]] > changes[tree[:, 1]]].tolist():
            yield length, places[x : y + 1]
        at = upto


def _surroundings(window: int, gram: int, buckets: int):
    """Packed bytes around the wanted anchors, by bucket of the anchor's hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def flush() -> pa.RecordBatch:
            h, doc, start, sizes = (np.concatenate([x[k] for x in held]) for k in range(4))
            raw = np.concatenate([x[4] for x in held])
            first = np.cumsum(sizes) - sizes
            bucket = (h // np.uint64(-(-(1 << 64) // buckets))).astype(np.int64)
            rows = []
            for k in np.unique(bucket):
                mine = np.flatnonzero(bucket == k)
                mine = mine[np.argsort(h[mine], kind="stable")]
                take = np.repeat(first[mine] - (np.cumsum(sizes[mine]) - sizes[mine]), sizes[mine]) + np.arange(int(sizes[mine].sum()))
                rows.append((int(k), pack_columns([h[mine], doc[mine], start[mine].astype(np.uint32), sizes[mine].astype(np.uint8)]), pack_columns([raw[take]])))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.binary(), pa.binary()), strict=True)], ["bucket", "packed", "raw"])

        for part in chunks(batches):
            data, offsets = text_buffer(part.column(1))
            ids = part.column(0).to_pylist()
            for k, blobs in enumerate(part.column(2).to_pylist()):
                pos, h, left, right = read_wanted(blobs or [])
                if not len(pos):
                    continue
                start, sizes = pos - left, left + right
                take = np.repeat(start - (np.cumsum(sizes) - sizes), sizes) + np.arange(int(sizes.sum())) + offsets[k]
                held.append((h, np.full(len(h), ids[k], np.int64), start, sizes, data[take]))
            if sum(len(x[4]) for x in held) > 8 << 20:
                yield flush()
                held = []
        if held:
            yield flush()

    return run


def _resolve(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs: dict[int, list] = {}
        for batch in batches:
            for bucket, packed, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                blobs.setdefault(bucket, []).append((packed, raw))
        for bucket in sorted(blobs):
            parts = [(*unpack_columns(p, [np.uint64, np.int64, np.uint32, np.uint8]), unpack_columns(r, [np.uint8])[0]) for p, r in blobs.pop(bucket)]
            h, doc, start, sizes = (np.concatenate([p[k] for p in parts]) for k in range(4))
            text, start, sizes = np.concatenate([p[4] for p in parts]), start.astype(np.int64), sizes.astype(np.int64)
            spans: list[tuple] = []
            # Anchors of one hash stay together; pieces of about 2 MB are worked through at a time.
            order = np.argsort(h, kind="stable")
            h, doc, start, sizes, first = h[order], doc[order], start[order], sizes[order], (np.cumsum(sizes) - sizes)[order]
            ends = np.cumsum(sizes)
            at = 0
            while at < len(h):
                upto = int(np.searchsorted(ends, ends[at] + (2 << 20)))
                upto = int(np.searchsorted(h, h[min(upto, len(h) - 1)], "right"))
                size = sizes[at:upto]
                bounds = np.concatenate([[0], np.cumsum(size)])
                take = np.repeat(first[at:upto] - bounds[:-1], size) + np.arange(int(bounds[-1]))
                for length, places in maximal_repeats(text[take], bounds, window):
                    piece = np.searchsorted(bounds, places, "right") - 1
                    d, p = doc[at:upto][piece], start[at:upto][piece] + places - bounds[piece]
                    low = d.min()
                    later = (d != low) | (p != p[d == low].min())
                    spans.append((d[later], p[later], p[later] + length))
                at = upto
            if spans:
                rows = list(span_marks(*(np.concatenate(c) for c in zip(*spans, strict=True))))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.binary()), strict=True)], ["doc_id", "kind", "packed"])
        release_memory()

    return run


def repeat_marks(docs: DataFrame, *, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """Packed removed stretches of each document."""
    own = docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).where("doc_id IS NOT NULL")
    marks = shared_marks(own, lambda part: byte_anchors(part, window, gram), within=True, name="byte-marks")
    buckets = buckets_of(docs)
    around = with_marks(own, marks, [WANTED], "inner").mapInArrow(_surroundings(window, gram, buckets), "bucket int, packed binary, raw binary")
    seen = written(around.repartitionById(buckets, "bucket").mapInArrow(_resolve(window), MARK), "byte-spans")
    return marks.where(F.col("kind") == COVER).unionByName(seen)


def cut_text(text: bytes, blobs: list[bytes]) -> tuple[bytes, np.ndarray, np.ndarray]:
    """What stays of a text, and the starts and stops of what goes."""
    start, stop = read_spans(blobs)
    edges = [0, *(x for pair in zip(start.tolist(), stop.tolist(), strict=True) for x in pair), len(text)]
    return b"".join(text[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)), start, stop


def byte_repeats(docs: DataFrame, *, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and the removed stretches of every row."""
    own, numbers = one_text_each(docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")))
    marks = repeat_marks(own, window=window, gram=gram)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            data, offsets = text_buffer(part.column(1))
            raw, rows = data.tobytes(), []
            for k, blobs in enumerate(part.column(2).to_pylist()):
                text = raw[offsets[k] : offsets[k + 1]]
                kept, start, stop = cut_text(text, blobs or [])
                rows.append((len(text), len(text) - len(kept), len(start), hashlib.sha256(kept).hexdigest(), [{"start": a, "stop": b} for a, b in zip(start.tolist(), stop.tolist(), strict=True)]))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())])))
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"])

    done = with_marks(own, marks, [COVER], "left").mapInArrow(finish, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start: long, stop: long>>")
    return given_ids(done, numbers)


def remove_repeats(docs: DataFrame, *, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """`docs` without repeated bytes in `text`; a character that a removed stretch cuts is dropped with it."""
    docs, numbers = one_text_each(docs)
    marked = with_marks(docs, repeat_marks(docs, window=window, gram=gram), [COVER], "left")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            at = part.schema.get_field_index("text")
            texts = part.column(at).to_pylist()
            blobs = part.column(part.num_columns - 1).to_pylist()  # the marks come last
            kept = [t if t is None or not b else cut_text(t.encode(), b)[0].decode("utf-8", "ignore") for t, b in zip(texts, blobs, strict=True)]
            columns = [pa.array(kept, part.schema.field(at).type) if k == at else part.column(k) for k in range(part.num_columns - 1)]
            yield pa.RecordBatch.from_arrays(columns, part.schema.names[:-1])

    return given_ids(marked.mapInArrow(cut, docs.schema), numbers)
