"""Fuzzy line dedup by MinHash: one line stays of every component of similar lines.

Lines are compared by their character shingles. A task hashes its distinct lines once: signatures of
`bands * rows` minima, cut into bands (at the default bands a pair at the threshold shares one with
probability 0.998), and a sketch of one bit each of 64 minima. Band keys with line identifiers, and the first
occurrence of each line, go to buckets in one shuffle of packed arrays; later occurrences of a line are
settled on the way, so a line that a third of all documents share costs one record for each part of a task.
Lines that share a band meet with their sketches: those with no partner whose sketch agrees in `AGREE` bits
(a pair at the threshold does with probability 0.9999) are dropped. The others' texts are fetched through a
bitmap of fixed size, their exact Jaccard similarity is checked, and union-find over the verified links gives
components: within a bucket first, then across the cluster by alternating stars. Of a component the line of
the smallest (doc_id, line number) stays.

Bands that the same lines share are verified once. A band that more than `BUCKET_LINES` lines share, or that
holds more than `BUCKET_CODES` shingles, is cut into blocks and every two blocks meet in a bucket of their
own, so no task holds more and no pair is left out. All buckets take the same path: pairs already connected
are skipped, a parity sketch gives a lower bound of the symmetric difference, the rest is counted exactly.

Defined cases: lines are compared without outer white space, with inner white space as one space and in
lower case; blank lines always stay; a line shorter than a shingle is one shingle; lines of any length are
compared whole; a null text has no lines; equal rows share their decisions, so that both keep a line that
occurs first in them; rows that share a doc_id but not their text are documents of their own, the smaller
hash first; ties go to the smaller line number; rows without doc_id are left as they are; an empty table
gives no rows; extra columns are ignored or, in `dedup_lines`, kept.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, mix64, release_memory, ship_package, text_or_empty, unused, written
from .components import connected_components
from .repeats import buckets_of, pack_columns, runs, unpack_columns

SHINGLE, BANDS, ROWS, THRESHOLD = 5, 16, 5, 0.8
#: Lines and shingles that one bucket of the verification holds at most (one pair of lines always fits).
BUCKET_LINES, BUCKET_CODES = 4096, 2 << 20
#: Bits of 64 in which the sketches of a candidate pair agree at least.
AGREE = 48
#: Kinds of packed records: line numbers that go, first occurrences of lines, lines of shared bands, band keys.
GONE, FIRST, SHARED, KEYS = 1, 2, 3, 4
#: Band keys that a task gathers before it packs them, and bits of the largest bitmap of wanted lines.
GATHER, LARGEST_BITMAP = 600_000, 1 << 28
_RECORD = "bucket int, doc_id long, version long, kind int, packed binary"
_MARK = "doc_id long, version long, kind int, packed binary"
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: White space other than space and line feed.
_SPACES = [chr(c) for c in range(0x3001) if chr(c).isspace() and chr(c) not in " \n"]


def canonical(line: str) -> str:
    return " ".join(line.lower().split())


def canonical_lines(text: str) -> list[str]:
    """All lines of a text in canonical form; most texts have no white space to tidy."""
    low = text.lower()
    lines = low.split("\n")
    if "  " in low or " \n" in low or "\n " in low or low[:1] == " " or low[-1:] == " " or any(c in low for c in _SPACES):
        return [" ".join(line.split()) for line in lines]
    return lines


def line_id(line: str) -> int:
    """A signed 64-bit identifier of a canonical line."""
    return int.from_bytes(hashlib.blake2b(line.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


def _ids(lines: list[str]) -> np.ndarray:
    raw = b"".join(hashlib.blake2b(line.encode("utf-8", "surrogatepass"), digest_size=8).digest() for line in lines)
    return np.frombuffer(raw, "<u8").astype(np.uint64)


def shingle_codes(lines: list[str], width: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Codes of all shingles of non-empty lines, one line after another, and n+1 bounds."""
    sizes = np.fromiter(map(len, lines), np.int64, len(lines))
    points = np.frombuffer("".join(lines).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    counts = np.maximum(sizes - width + 1, 1)
    bounds = np.concatenate([[0], np.cumsum(counts)])
    begins = np.cumsum(sizes) - sizes
    at = np.repeat(begins - bounds[:-1], counts) + np.arange(int(bounds[-1]))
    # Codes of 1, 2, 4, ... characters from every place on, then two of them that overlap or touch make the width.
    value, span = np.concatenate([points + np.uint64(1), np.zeros(width, np.uint64)]), 1
    while 2 * span <= width:
        value = value[: len(value) - span] * _ODD + value[span:]
        value ^= value >> np.uint64(31)
        span *= 2
    if span < width:
        value = value[: len(value) - (width - span)] * _ODD + value[width - span :]
    value ^= value >> np.uint64(32)
    value *= np.uint64(0xFF51AFD7ED558CCD)
    value ^= value >> np.uint64(29)
    code = value[np.minimum(at, len(value) - 1)]
    short = np.flatnonzero(sizes < width)
    for i in short:  # the whole line is the shingle
        whole = int(sizes[i])
        for c in points[begins[i] : begins[i] + sizes[i]].tolist():
            whole = (whole * int(_ODD) ^ c) % (1 << 64)
        code[bounds[i]] = whole
    code[bounds[short]] = mix64(code[bounds[short]])
    return code, bounds


def signature(code: np.ndarray, bounds: np.ndarray, bands: int, rows: int, seed: int, block: int = 1 << 15) -> tuple[np.ndarray, np.ndarray]:
    """Band hashes of each set of codes, one column per band, and its sketch: a bit each of 64 minima, in turn."""
    code = (code >> np.uint64(32)).astype(np.uint32)
    n = len(bounds) - 1
    least = np.empty((bands * rows, n), np.uint32)
    factors = np.random.default_rng(seed).integers(0, 1 << 31, bands * rows).astype(np.uint32) * np.uint32(2) + np.uint32(1)
    edges = np.unique(np.searchsorted(bounds, [*range(0, int(bounds[-1]), block), int(bounds[-1])]))
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist()):  # whole sets, about `block` codes at a time: they stay in the cache
        part, first = code[bounds[a] : bounds[b]], bounds[a:b] - bounds[a]
        held = np.empty_like(part)
        for k, factor in enumerate(factors):
            np.multiply(part, factor, out=held)
            np.minimum.reduceat(held, first, out=least[k, a:b])
    keys, sketch = np.zeros((n, bands), np.uint64), np.zeros(n, np.uint64)
    for band in range(bands):
        key = np.full(n, band + 1, np.uint64)
        for row in range(rows):
            key = mix64(key * _ODD ^ least[band * rows + row])
        keys[:, band] = key
    for k in range(64):
        sketch |= (least[k % len(least)] * np.uint32(0x9E3779B1 + 2 * (k // len(least))) >> np.uint32(31)).astype(np.uint64) << np.uint64(k)
    return keys, sketch


def band_keys(lines: list[str], bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """Band hashes of each line, one column per band."""
    return signature(*shingle_codes(lines), bands, rows, 20)[0]


def _step(buckets: int) -> np.uint64:
    """Values per bucket where 64-bit values are dealt out by their size."""
    return np.uint64(-(-(1 << 64) // buckets))


def _records(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    fields = [f.split() for f in schema.split(", ")]
    columns = list(zip(*rows, strict=True)) or [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(columns, fields, strict=True)], [n for n, _ in fields])


def _settle(line: np.ndarray, doc: np.ndarray, version: np.ndarray, number: np.ndarray, *facts: np.ndarray) -> tuple[tuple, tuple]:
    """First occurrences of lines, and the other ones; occurrences given twice count once."""
    order = np.lexsort((number, version, doc, line))
    line, doc, version, number, *facts = (c[order] for c in (line, doc, version, number, *facts))
    fresh, same = np.ones(len(line), bool), np.zeros(len(line), bool)
    fresh[1:] = line[1:] != line[:-1]
    same[1:] = ~fresh[1:] & (doc[1:] == doc[:-1]) & (version[1:] == version[:-1]) & (number[1:] == number[:-1])
    first, later = np.flatnonzero(fresh), np.flatnonzero(~(fresh | same))
    return tuple(c[first] for c in (line, doc, version, number, *facts)), tuple(c[later] for c in (doc, version, number))


def _gone_marks(doc: np.ndarray, version: np.ndarray, number: np.ndarray) -> Iterator[tuple[int, int, int, bytes]]:
    order = np.lexsort((number, version, doc))
    doc, version, number = doc[order], version[order], number[order]
    edge = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (version[1:] != version[:-1])])) if len(doc) else []
    for a, b in zip(edge, [*edge[1:], len(doc)]):
        yield int(doc[a]), int(version[a]), GONE, number[a:b].astype("<u4").tobytes()


def _pack_firsts(line: np.ndarray, doc: np.ndarray, version: np.ndarray, number: np.ndarray, sketch: np.ndarray, size: np.ndarray) -> bytes:
    order = np.lexsort((version, doc))
    a, b = doc[order], version[order]
    fresh = np.ones(len(a), bool)
    fresh[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    which = np.empty(len(a), np.uint32)
    which[order] = np.cumsum(fresh) - 1
    table = pack_columns([a[fresh], b[fresh]])
    return len(table).to_bytes(4, "big") + table + pack_columns([line, which, number.astype(np.uint32), sketch, size.astype(np.uint32)])


def _unpack_firsts(blob: bytes) -> tuple[np.ndarray, ...]:
    """Line, document, version, number, sketch, size."""
    at = int.from_bytes(blob[:4], "big")
    doc, version = unpack_columns(blob[4 : 4 + at], [np.int64, np.int64])
    line, which, number, sketch, size = unpack_columns(blob[4 + at :], [np.uint64, np.uint32, np.uint32, np.uint64, np.uint32])
    return line, doc[which], version[which], number.astype(np.int64), sketch, size


def _gather(bands: int, rows: int, buckets: int):
    """Packed band keys and first occurrences of each part of a task, by bucket, and the later occurrences in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, tuple[int, int]] = {}  # sketch and size of the lines whose keys this task has sent
        places: list[tuple] = []
        entries: list[tuple] = []

        def flush() -> pa.RecordBatch:
            first, later = _settle(*(np.concatenate(c) for c in zip(*places, strict=True)))
            out = [(doc % buckets, doc, version, kind, packed) for doc, version, kind, packed in _gone_marks(*later)]
            edges = np.searchsorted(first[0] // _step(buckets), np.arange(buckets + 1, dtype=np.uint64))
            out += [(k, None, None, FIRST, _pack_firsts(*(c[a:b] for c in first))) for k, (a, b) in enumerate(zip(edges, edges[1:])) if b > a]
            if entries:
                key, line = (np.concatenate(c) for c in zip(*entries, strict=True))
                order = np.argsort(key, kind="stable")
                key, line = key[order], line[order]
                edges = np.searchsorted(key // _step(buckets), np.arange(buckets + 1, dtype=np.uint64))
                out += [(k, None, None, KEYS, pack_columns([key[a:b], line[a:b]])) for k, (a, b) in enumerate(zip(edges, edges[1:])) if b > a]
            places.clear()
            entries.clear()
            return _records(out, _RECORD)

        held = 0
        for part in chunks(batches):
            own: dict[str, int] = {}
            which, counts, numbers = [], [], []
            for text in part.column(2).to_pylist():
                lines = canonical_lines(text)
                kept = [at for at, line in enumerate(lines) if line]
                which += [own.setdefault(lines[at], len(own)) for at in kept]
                counts.append(len(kept))
                numbers += kept
            if not own:
                continue
            ids, names = _ids(list(own)), list(own)
            listed = ids.tolist()
            if len(known) > 300_000:  # bounds memory; keys sent again do no harm
                known.clear()
            fresh = [k for k, i in enumerate(listed) if i not in known]
            if fresh:
                code, bounds = shingle_codes([names[k] for k in fresh])
                keys, sketch = signature(code, bounds, bands, rows, 20)
                entries.append((keys.ravel(), np.repeat(ids[fresh], bands)))
                held += keys.size
                known.update(zip((listed[k] for k in fresh), zip(sketch.tolist(), np.diff(bounds).tolist(), strict=True), strict=True))
            facts = [known[i] for i in listed]
            sketch, size = np.array([f[0] for f in facts], np.uint64), np.array([f[1] for f in facts], np.uint32)
            doc, version = (np.repeat(part.column(k).to_numpy(), counts) for k in (0, 1))
            at = np.array(which)
            places.append((ids[at], doc, version, np.array(numbers, np.int64), sketch[at], size[at]))
            if held > GATHER or sum(len(p[0]) for p in places) > GATHER:
                yield flush()
                held = 0
        if places:
            yield flush()

    return run


def blocks_of(size: np.ndarray, lines: int = BUCKET_LINES, codes: int = BUCKET_CODES) -> np.ndarray:
    """Block number of each member of a bucket; any two blocks together stay within the limits."""
    block = np.zeros(len(size), np.int64)
    if len(size) <= lines and size.sum() <= codes:
        return block
    at = held = weight = 0
    for k, own in enumerate(size.tolist()):
        if held and (held >= lines // 2 or weight + own > codes // 2):
            at, held, weight = at + 1, 0, 0
        block[k], held, weight = at, held + 1, weight + own
    return block


def shared(key: np.ndarray, line: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The entries, sorted and each once, whose key different lines have."""
    ranked = np.sort(key)
    twice = ranked[1:][ranked[1:] == ranked[:-1]]
    if not len(twice):
        return key[:0], line[:0]
    at = np.searchsorted(twice, key)
    some = np.flatnonzero(twice[np.minimum(at, len(twice) - 1)] == key)
    order = some[np.lexsort((line[some], key[some]))]
    key, line = key[order], line[order]
    fresh = np.concatenate([[True], (key[1:] != key[:-1]) | (line[1:] != line[:-1])])
    key, line = key[fresh], line[fresh]
    again = np.concatenate([[False], key[1:] == key[:-1]])
    kept = again | np.concatenate([again[1:], [False]])
    return key[kept], line[kept]


def near_members(key: np.ndarray, fact: np.ndarray, near) -> np.ndarray:
    """Places (entries sorted by key) that have a partner of the same key: `near` judges the xor of their facts.

    Places at distance 1, 2, ... are compared for all keys at once, until all of a key have partners.
    """
    kept = np.zeros(len(key), bool)
    gap = 1
    while gap < len(key):
        within = np.flatnonzero(key[gap:] == key[:-gap])
        if not len(within):
            break
        open_ = within[~(kept[within] & kept[within + gap])]
        found = open_[near(fact[open_] ^ fact[open_ + gap])]
        kept[found] = kept[found + gap] = True
        gap += 1
    return np.flatnonzero(kept)


def verification_buckets(key: np.ndarray, line: np.ndarray, size: np.ndarray, lines: int = BUCKET_LINES, codes: int = BUCKET_CODES) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, line) from entries sorted by key; equal sets of lines make one bucket, large ones are cut."""
    if not len(key):
        return key, line
    first, stop = runs(key)
    count, weight = stop - first, np.add.reduceat(size.astype(np.int64), first)
    bucket = mix64(np.add.reduceat(mix64(line), first) ^ count.astype(np.uint64))
    chosen = np.zeros(len(bucket), bool)
    chosen[np.unique(bucket, return_index=True)[1]] = True
    chosen &= count > 1
    plain = chosen & (count <= lines) & (weight <= codes)
    out = [(np.repeat(bucket[plain], count[plain]), line[np.repeat(plain, count)])]
    for k in np.flatnonzero(chosen & ~plain):
        own = slice(first[k], stop[k])
        block = blocks_of(size[own].astype(np.int64), lines, codes)
        for i in range(int(block[-1]) + 1):
            for j in range(i + 1, int(block[-1]) + 1):
                both = line[own][(block == i) | (block == j)]
                out.append((np.full(len(both), mix64(np.array([int(bucket[k]) ^ (i << 32 | j)], np.uint64))[0]), both))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def meeting(near):
    """(home, key, id) of the buckets to verify, from rows (key, id, fact, size) that are partitioned by key.

    The home of a bucket is its least line: buckets of one home share most of their lines and are verified together.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [tuple(c.to_numpy().view(np.uint64) for c in b.columns) for b in batches]
        if parts:
            key, line, fact, size = (np.concatenate(c) for c in zip(*parts, strict=True))
            order = np.lexsort((line, fact, key))
            order = order[near_members(key[order], fact[order], near)]
            order = order[np.lexsort((line[order], key[order]))]
            key, line = verification_buckets(key[order], line[order], size[order])
            first, stop = runs(key)
            home = np.repeat(np.minimum.reduceat(line, first), stop - first) if len(key) else line
            yield pa.RecordBatch.from_arrays([pa.array(c.view(np.int64)) for c in (home, key, line)], ["home", "key", "id"])
        release_memory()

    return run


def _judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Marks of each bucket of packed records."""
    firsts: dict[int, list[bytes]] = {}
    keys: dict[int, list[bytes]] = {}
    for batch in batches:
        passed = []
        for bucket, doc, version, kind, packed in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if kind == GONE:
                passed.append((doc, version, kind, packed))
            else:
                (firsts if kind == FIRST else keys).setdefault(bucket, []).append(packed)
        if passed:
            yield _records(passed, _MARK)
    for bucket in sorted(firsts):
        first, later = _settle(*(np.concatenate(c) for c in zip(*(_unpack_firsts(b) for b in firsts.pop(bucket)), strict=True)))
        yield _records([*_gone_marks(*later), (None, None, FIRST, _pack_firsts(*first))], _MARK)
    for bucket in sorted(keys):
        parts = [unpack_columns(b, [np.uint64, np.uint64]) for b in keys.pop(bucket)]
        key, line = shared(*(np.concatenate(c) for c in zip(*parts, strict=True)))
        if len(key):
            yield _records([(None, None, SHARED, pack_columns([key, line]))], _MARK)
    release_memory()


def _unpack_shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for blob in batch.column(0).to_pylist():
            key, line = unpack_columns(blob, [np.uint64, np.uint64])
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(line.view(np.int64))], ["key", "id"])


def bitmap_of(ids: DataFrame, parts: int = 16) -> tuple[bytes, int]:
    """A bitmap of the ids (column id) by their leading bits, and the number of bits that select one.

    Eight bits an id, up to `LARGEST_BITMAP` bits; beyond that it selects more rows than asked for, never fewer.
    """
    wanted = 8 * ids.count()
    bits = int(min(max(wanted, 1 << 16), LARGEST_BITMAP) - 1).bit_length()
    span = (1 << bits) // parts

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[int, np.ndarray] = {}
        for batch in batches:
            slot = (batch.column(1).to_numpy().view(np.uint64) >> np.uint64(64 - bits)).astype(np.int64)
            for part in np.unique(slot // span).tolist():
                own.setdefault(part, np.zeros(span, bool))[slot[slot // span == part] % span] = True
        for part, seen in own.items():
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([np.packbits(seen).tobytes()], pa.binary())], ["part", "bits"])

    dealt = ids.select(F.shiftrightunsigned("id", 64 - (parts.bit_length() - 1)).cast("int").alias("part"), "id").repartitionById(parts, "part")
    rows = {r["part"]: r["bits"] for r in dealt.mapInArrow(mark, "part int, bits binary").toLocalIterator()}
    return b"".join(rows.get(k, bytes(span // 8)) for k in range(parts)), bits


def _selected(ids: np.ndarray, bitmap: np.ndarray, bits: int) -> np.ndarray:
    slot = (ids >> np.uint64(64 - bits)).astype(np.int64)
    return np.flatnonzero(bitmap[slot >> 3] >> (7 - (slot & 7)).astype(np.uint8) & 1)


def _wanted_texts(sent):
    """(id, canonical text) of the lines that the bitmap selects, once for each part of a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bitmap, bits = np.frombuffer(sent.value[0], np.uint8), sent.value[1]
        for part in chunks(batches):
            lines = list({line for text in part.column(0).to_pylist() for line in canonical_lines(text) if line})
            ids = _ids(lines)
            found = _selected(ids, bitmap, bits)
            if len(found):
                yield pa.RecordBatch.from_arrays([pa.array(ids[found].view(np.int64)), pa.array([lines[k] for k in found], pa.string())], ["id", "plain"])

    return run


def _firsts(sent, sketches: bool):
    """(id, sketch, size) or (id, doc_id, version, line) of the first occurrences that the bitmap selects."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bitmap, bits = np.frombuffer(sent.value[0], np.uint8), sent.value[1]
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                line, doc, version, number, sketch, size = _unpack_firsts(blob)
                at = _selected(line, bitmap, bits)
                own = pa.array(line[at].view(np.int64))
                if sketches:
                    yield pa.RecordBatch.from_arrays([own, pa.array(sketch[at].view(np.int64)), pa.array(size[at].astype(np.int64))], ["id", "sketch", "size"])
                else:
                    yield pa.RecordBatch.from_arrays([own, pa.array(doc[at]), pa.array(version[at]), pa.array(number[at].astype(np.int32))], ["id", "doc_id", "version", "line"])

    return run


def sorted_sets(code: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct codes (of 44 bits) of each set, in order, and n+1 bounds; up to 2**20 sets."""
    owner = np.repeat(np.arange(len(bounds) - 1, dtype=np.uint64), np.diff(bounds))
    both = np.sort(owner << np.uint64(44) | code >> np.uint64(20))
    both = both[np.concatenate([[True], both[1:] != both[:-1]])] if len(both) else both
    return both & np.uint64((1 << 44) - 1), np.searchsorted(both >> np.uint64(44), np.arange(len(bounds), dtype=np.uint64))


def parity_sketches(code: np.ndarray, bounds: np.ndarray, bits: int) -> np.ndarray:
    """A row of 64-bit words for each set: bit b is the parity of the codes that fall on b.

    Two rows differ in at most as many bits as the symmetric difference of their sets has codes.
    """
    owner = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    flips = np.bincount(owner * bits + (code % np.uint64(bits)).astype(np.int64), minlength=(len(bounds) - 1) * bits) & 1
    return np.packbits(flips.astype(np.uint8).reshape(-1, bits), axis=1).view(np.uint64)


def set_links(bucket: np.ndarray, member: np.ndarray, code: np.ndarray, bounds: np.ndarray, threshold: float) -> list[tuple[int, int]]:
    """Pairs of sets that connect what the similar pairs within the buckets connect.

    `bucket` is sorted; `member` gives the set at each place of a bucket. Places at distance 1, 2, ... are
    compared for all buckets at once; pairs whose sets are connected already are skipped.
    """
    code, bounds = sorted_sets(code, bounds)
    size = np.diff(bounds)
    bits = 1 << max(8, min(int(np.median(size, keepdims=False)) if len(size) else 1, 1 << 14).bit_length())
    sketch = parity_sketches(code, bounds, bits)
    root = np.arange(len(size))
    slack = (1 - threshold) / (1 + threshold)
    links: list[tuple[int, int]] = []
    gap = 1
    while True:
        left = np.flatnonzero(bucket[gap:] == bucket[:-gap]) if gap < len(bucket) else np.zeros(0, np.int64)
        if not len(left):
            return links
        a, b = member[left], member[left + gap]
        apart = root[a] != root[b]
        a, b = a[apart], b[apart]
        for at in range(0, len(a), 4096):
            x, y = a[at : at + 4096], b[at : at + 4096]
            differing = np.bitwise_count(sketch[x] ^ sketch[y]).sum(1, dtype=np.int64)
            near = differing <= slack * (size[x] + size[y]) + 1e-9
            for i, j in zip(x[near].tolist(), y[near].tolist()):
                if root[i] == root[j]:
                    continue
                one, two = code[bounds[i] : bounds[i + 1]], code[bounds[j] : bounds[j + 1]]
                where = np.searchsorted(one, two)
                common = int((one[np.minimum(where, len(one) - 1)] == two).sum())
                if common >= threshold * (len(one) + len(two) - common) - 1e-9:
                    links.append((i, j))
                    low, high = sorted((int(root[i]), int(root[j])))
                    root[root == high] = low
        gap += 1


def _verify(threshold: float, coded, step: int = 2000):
    """Links among the rows (home, key, id, text), sorted by home and key, of a task; `coded` gives texts' shingle codes."""

    def check(waiting: list[tuple[int, list[tuple[int, str]]]]) -> pa.RecordBatch:
        texts = {line: text for _, members in waiting for line, text in members}
        ids = np.array(sorted(texts), np.int64)
        code, bounds = coded([texts[i] for i in ids.tolist()])
        bucket = np.repeat(np.arange(len(waiting)), [len(members) for _, members in waiting])
        member = np.searchsorted(ids, np.array([line for _, members in waiting for line, _ in members], np.int64))
        links = np.array(set_links(bucket, member, code, bounds, threshold), np.int64).reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(ids[links.min(1)]), pa.array(ids[links.max(1)])], ["lo", "hi"]) if len(links) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (r for b in batches for at in range(0, b.num_rows, 500) for r in zip(*(c.to_pylist() for c in b.slice(at, 500).columns), strict=True))
        waiting, held, weight, last = [], 0, 0, None
        for (home, key), group in groupby(rows, key=lambda r: r[:2]):
            members = [(line, text) for _, _, line, text in group]
            own = sum(len(text) for _, text in members)
            most = step if home != last else 2 * step  # buckets of one home stay together if they can
            if waiting and (held + len(members) > most or weight + own > most << 8):
                if (found := check(waiting)) is not None:
                    yield found
                waiting, held, weight = [], 0, 0
            waiting.append((key, members))
            held, weight, last = held + len(members), weight + own, home
        if waiting and (found := check(waiting)) is not None:
            yield found
        release_memory()

    return run


def _own(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), F.xxhash64(text_or_empty()).alias("version"), text_or_empty().alias("text"))


def removed_lines(docs: DataFrame, *, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, version, removed): sorted numbers, from 0, of the lines that go from texts of that hash; others are absent."""
    spark = docs.sparkSession
    ship_package(spark)
    tasks, buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8), buckets_of(docs)
    own = _own(docs).where("doc_id IS NOT NULL")
    marks = written(own.mapInArrow(_gather(bands, rows, buckets), _RECORD).repartitionById(buckets, "bucket").mapInArrow(_judge, _MARK), "line-marks")
    firsts = marks.where(F.col("kind") == FIRST).select("packed")
    entries = written(marks.where(F.col("kind") == SHARED).select("packed").mapInArrow(_unpack_shared, "key long, id long"), "line-entries")
    meets = spark.sparkContext.broadcast(bitmap_of(entries.select("id")))  # of LARGEST_BITMAP bits at most, like the next one
    sketched = entries.join(firsts.mapInArrow(_firsts(meets, True), "id long, sketch long, size long"), "id").select("key", "id", "sketch", "size")
    agree = lambda differing: np.bitwise_count(differing) <= 64 - AGREE
    candidates = written(sketched.repartition(tasks, "key").mapInArrow(meeting(agree), "home long, key long, id long").distinct(), "line-candidates")
    sent = spark.sparkContext.broadcast(bitmap_of(candidates.select("id")))
    texts = own.select("text").mapInArrow(_wanted_texts(sent), "id long, plain string").dropDuplicates(["id"])
    placed = candidates.join(texts, "id").select("home", "key", "id", "plain").repartition(tasks, "home").sortWithinPartitions("home", "key")
    roots = connected_components(placed.mapInArrow(_verify(threshold, shingle_codes), "lo long, hi long"), "line-components")
    members = roots.select(F.col("node").alias("id"), "root").unionByName(roots.select(F.col("root").alias("id"), "root").distinct())
    places = firsts.mapInArrow(_firsts(sent, False), "id long, doc_id long, version long, line int")
    grouped = written(members.join(places, "id").select("root", F.struct("doc_id", "version", "line").alias("place")), "line-groups")
    keepers = grouped.groupBy(F.col("root").alias("of")).agg(F.min("place").alias("keeper"))
    fuzzy = grouped.join(keepers, F.col("root") == F.col("of")).where("place != keeper").select("place.doc_id", "place.version", "place.line")
    exact = marks.where(F.col("kind") == GONE).select("doc_id", "version", "packed").mapInArrow(_numbers, "doc_id long, version long, line int")
    return exact.unionByName(fuzzy).groupBy("doc_id", "version").agg(F.array_sort(F.collect_set("line")).alias("removed"))


def _numbers(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        lines = [np.frombuffer(blob, "<u4").astype(np.int32) for blob in batch.column(2).to_pylist()]
        which = pa.array(np.repeat(np.arange(len(lines)), [len(x) for x in lines]))
        yield pa.RecordBatch.from_arrays([batch.column(0).take(which), batch.column(1).take(which), pa.array(np.concatenate(lines) if lines else np.zeros(0, np.int32))], ["doc_id", "version", "line"])


def line_decisions(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_lines, n_removed and the numbers of the removed lines of every row."""
    gone = removed_lines(docs, **options).select(F.col("doc_id").alias("_at"), F.col("version").alias("_version"), "removed")
    breaks = F.length(F.col("text")) - F.length(F.replace(F.col("text"), F.lit("\n")))
    counted = _own(docs).select("doc_id", "version", F.when(F.length("text") == 0, 0).otherwise(breaks + 1).cast("long").alias("n_lines"))
    joined = counted.join(gone, (F.col("doc_id") == F.col("_at")) & (F.col("version") == F.col("_version")), "left")
    return joined.select("doc_id", "n_lines", F.coalesce(F.size("removed"), F.lit(0)).cast("long").alias("n_removed"), F.coalesce("removed", F.array().cast("array<int>")).alias("removed_lines"))


def dedup_lines(docs: DataFrame, **options) -> DataFrame:
    """`docs` with the removed lines taken out of `text`; other columns as they are."""
    at, version, out = unused(docs, "_at"), unused(docs, "_version"), unused(docs, "_removed")
    gone = removed_lines(docs, **options).select(F.col("doc_id").alias(at), F.col("version").alias(version), F.col("removed").alias(out))
    same = (F.col("doc_id").cast("long") == F.col(at)) & (F.xxhash64(text_or_empty()) == F.col(version))
    marked = docs.join(gone, same, "left").select(*(F.col(f"`{c}`") for c in docs.columns), out)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            where = part.schema.get_field_index("text")
            texts, kept = part.column(where).to_pylist(), []
            for text, lost in zip(texts, part.column(part.num_columns - 1).to_pylist(), strict=True):
                if lost:
                    goes = set(lost)
                    text = "\n".join(line for number, line in enumerate(text.split("\n")) if number not in goes)
                kept.append(text)
            columns = [pa.array(kept, part.schema.field(k).type) if k == where else part.column(k) for k in range(part.num_columns - 1)]
            yield pa.RecordBatch.from_arrays(columns, part.schema.names[:-1])

    return marked.mapInArrow(cut, docs.schema)
