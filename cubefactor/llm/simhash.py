"""SimHash near-duplicates with pigeonring filtering.

A fingerprint is the bitwise majority of the hashes of a document's word shingles. Fingerprints within
`threshold` differing bits are linked. Their 64 bits form a ring of `threshold + 1` segments. By the
pigeonring principle two fingerprints within the threshold have a segment from which every chain of
consecutive segments stays within its proportional budget (chain length times threshold over the number of
segments, rounded down): the first segment is equal, the first two differ in at most one bit, and so on.
The first two budgets make the join key: fingerprints are indexed by two neighbouring segments and probed
with each one-bit change of the second. Longer chains are checked before the full Hamming distance.

Rows are distinct fingerprints, so exact copies cost nothing. Probes and index entries of one key meet in
one task, where all runs take the same path whatever their size, and only a spanning forest of the links
leaves the task: a dense group of g fingerprints gives fewer than g rows per key, not g squared.

Defined cases: a null or empty text has fingerprint zero, linked like any other; with fewer words than a
shingle the whole sequence is the shingle; repeated rows share a component; a null doc_id is kept and its
component is null unless a row with an id is reachable; an empty table gives no rows; extra columns are
ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, keep_least, release_memory, row_hash, ship_package, text_buffer, text_or_empty, written
from .components import connected_components, forest

SHINGLE, THRESHOLD, SEED = 4, 4, 42


def fingerprints_of(texts: pa.Array, shingle: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """The 64-bit fingerprint of each text, unsigned."""
    data, offsets = text_buffer(texts)
    raw, digest = data.tobytes(), xxhash.xxh64_intdigest
    hashes: list[int] = []
    counts = np.zeros(len(offsets) - 1, np.int64)
    for number, (a, b) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)):
        words = raw[a:b].lower().split()
        if not words:
            continue
        joined = b" ".join(words)
        ends = list(accumulate(len(w) + 1 for w in words))
        if len(words) <= shingle:
            hashes.append(digest(joined, seed))
            counts[number] = 1
            continue
        starts = [0, *ends[: len(words) - shingle]]
        hashes += [digest(joined[s : e - 1], seed) for s, e in zip(starts, ends[shingle - 1 :], strict=True)]
        counts[number] = len(words) - shingle + 1
    out = np.zeros(len(counts), np.uint64)
    some = np.flatnonzero(counts)
    if len(some):
        bits = np.unpackbits(np.array(hashes, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        first = np.cumsum(counts[some]) - counts[some]
        ones = np.add.reduceat(bits, first, axis=0, dtype=np.int64)
        majority = (2 * ones > counts[some][:, None]).astype(np.uint8)
        out[some] = np.packbits(majority, axis=1, bitorder="little").view("<u8").ravel()
    return out


def fingerprint(docs: DataFrame, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """doc_id and fp (the fingerprint's bits as a signed long) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fingerprints_of(part.column(1), shingle, seed).view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(run, "doc_id long, fp long")


def ring(threshold: int) -> list[tuple[int, int]]:
    """(shift, width) of the segments around the ring."""
    parts = threshold + 1
    edges = [64 * k // parts for k in range(parts + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:])]


def _segment(fp: np.ndarray, segment: tuple[int, int]) -> np.ndarray:
    return (fp >> np.uint64(segment[0])) & np.uint64((1 << segment[1]) - 1)


def chain_ok(differing: np.ndarray, start: int, segments: list[tuple[int, int]], threshold: int) -> np.ndarray:
    """Whether all chains from segment `start` stay within their budgets, given the xor of fingerprints."""
    total, ok, parts = np.zeros(len(differing), np.int64), np.ones(len(differing), bool), len(segments)
    for length in range(1, parts + 1):
        total += np.bitwise_count(_segment(differing, segments[(start + length - 1) % parts]))
        ok &= total <= length * threshold // parts
    return ok


def _entries(threshold: int):
    """Index and probe entries of a batch of fingerprints: key (ring position and two segments), fp, probe flag."""
    segments = ring(threshold)
    parts = len(segments)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 20_000):
                fp = np.asarray(batch.column(0).slice(at, 20_000)).view(np.uint64)
                for start in range(parts):
                    first, second = segments[start], segments[(start + 1) % parts]
                    two = np.uint64(2 * threshold // parts)
                    head = (np.uint64(start) << np.uint64(60)) | (_segment(fp, first) << np.uint64(second[1]))
                    tail = _segment(fp, second)
                    # Of two segments that differ in one bit, the one without the bit probes for the other.
                    bits = [np.uint64(1) << np.uint64(j) for j in range(second[1])] if two else []
                    lacking = [np.flatnonzero((tail & bit) == 0) for bit in bits]
                    keys = np.concatenate([head | tail, *((head | tail | bit)[at_] for bit, at_ in zip(bits, lacking, strict=True))])
                    who = np.concatenate([fp, *(fp[at_] for at_ in lacking)])
                    yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(who.view(np.int64)), pa.array(np.arange(len(who)) >= len(fp))], ["key", "fp", "probe"])

    return run


def link_entries(key: np.ndarray, fp: np.ndarray, probe: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Forest of the links among entries of equal key.

    Entries at distance 1, 2, ... in their key's run are compared for all runs at once: chains from the key's
    segment first, then the full distance. Entries that are connected already are skipped, and a run whose
    entries are all connected is left.
    """
    segments = ring(threshold)
    order = np.lexsort((fp, key))
    key, fp, probe = key[order], fp[order], probe[order]
    value = fp.view(np.uint64)
    start = (key.view(np.uint64) >> np.uint64(60)).astype(np.int64)
    names, node = np.unique(fp, return_inverse=True)
    root = np.arange(len(names))
    place = np.arange(len(key))
    low, high = [names[:0]], [names[:0]]
    gap = 1
    while len(place) > gap:
        mine, other = place[:-gap], place[gap:]
        within = key[mine] == key[other]
        if not within.any():
            break
        mine, other = mine[within], other[within]
        open_ = (root[node[mine]] != root[node[other]]) & ~(probe[mine] & probe[other])
        mine, other = mine[open_], other[open_]
        differing = value[mine] ^ value[other]
        near = np.ones(len(mine), bool)
        for s in range(len(segments)):
            here = start[mine] == s
            near[here] = chain_ok(differing[here], s, segments, threshold)
        near &= np.bitwise_count(differing) <= threshold
        if near.any():
            a, b = forest(root[node[mine[near]]], root[node[other[near]]])
            low.append(names[a])
            high.append(names[b])
            moved = np.arange(len(names))
            moved[b] = a
            root = moved[root]
            edge = np.flatnonzero(np.concatenate([[True], key[place][1:] != key[place][:-1]]))
            owner = root[node[place]]
            done = np.minimum.reduceat(owner, edge) == np.maximum.reduceat(owner, edge)
            place = place[np.repeat(~done, np.diff(np.append(edge, len(place))))]
        gap += 1
    return forest(np.concatenate(low), np.concatenate(high))


def fingerprint_links(distinct: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """Links (lo, hi) that connect all distinct fingerprints (column fp) within the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(np.asarray(b.column(0)), np.asarray(b.column(1)), b.column(2).to_numpy(zero_copy_only=False)) for b in batches]
        if parts:
            low, high = link_entries(*(np.concatenate(c) for c in zip(*parts, strict=True)), threshold)
            yield pa.RecordBatch.from_arrays([pa.array(low), pa.array(high)], ["lo", "hi"])
        release_memory()

    spark = distinct.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8) * 2
    entries = distinct.select("fp").mapInArrow(_entries(threshold), "key long, fp long, probe boolean")
    return entries.repartition(tasks, "key").mapInArrow(run, "lo long, hi long")


def near_duplicates(docs: DataFrame, *, shingle: int = SHINGLE, threshold: int = THRESHOLD, seed: int = SEED) -> DataFrame:
    """doc_id, fingerprint in hex, and component_id: the smallest doc_id reachable over links."""
    ship_package(docs.sparkSession)
    marked = written(fingerprint(docs, shingle, seed), "fingerprints")
    distinct = written(marked.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    roots = connected_components(fingerprint_links(distinct, threshold), "fingerprint-components", shrink=False)
    members = distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = members.groupBy("root").agg(F.min("least").alias("component_id"))
    found = written(members.join(least, "root").select(F.col("fp").alias("own"), "component_id"), "fingerprint-groups")
    return marked.join(found, F.col("fp") == F.col("own")).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, **options) -> DataFrame:
    """One row of each group: of the smallest doc_id, and of rows that share it the one of the smallest hash; rows without doc_id stay."""
    own = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), row_hash(docs).alias("tie"), "text")
    groups = near_duplicates(own.select(F.col("tie").alias("doc_id"), "text"), **options).select(F.col("doc_id").alias("of"), F.col("component_id").alias("grp")).distinct()
    return keep_least(docs, own.join(groups, F.col("tie") == F.col("of")).select("doc_id", "tie", "grp"))
