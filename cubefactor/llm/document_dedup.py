"""SimHash near-dedup of documents at a stated similarity: links are pairs of Jaccard similarity `threshold` or more.

A fingerprint has 1,280 bits, each the majority of one bit of a document's distinct five-word shingles. A pair at
Jaccard 0.8 differs in about 0.15 of them, 194 of standard deviation 13; `BUDGET` allows 320. The fingerprint is a ring of
80 segments of 16 bits. By the pigeonring principle a pair within 320 bits has a segment from which all chains of
consecutive segments stay within their proportional budgets, 4 bits a segment. Documents meet at the segments they
have in common (`KEY_BITS` of a segment are equal, and 64 bits are too few for that: two of their segments would select a
few hundredths of all documents): a pair at the threshold has one with probability 0.9998. Majorities over
very few shingles differ more, so documents of up to `FEW` also meet at the segments that begin midway. There chains of up to `CHAIN` segments from the common one must stay within their budgets, which two
unrelated documents do about once in 200,000 meetings. What is left is fetched and compared exactly. Groups are
the connected components of the exact links.

Equal word sequences have one identifier and are one row from the start. Large groups are cut into blocks that
meet two by two, and verified as in `line_dedup`; of a bucket's links only a forest leaves.

Defined cases: words are compared in lower case, whatever white space parts them; a document of fewer words
than a shingle is one shingle; null and empty texts are equal; texts of any length are compared whole; rows
without doc_id stay; of a group one row stays, that of the smallest doc_id, and of rows that share it the one
of the smallest hash of all columns; an empty table gives no rows; extra columns are kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, keep_least, mix64, release_memory, row_bounds, row_hash, ship_package, span_hashes, text_buffer, text_or_empty, word_spans, written
from .components import connected_components
from .line_dedup import _verify, near_members, runs, sorted_sets, verification_buckets

SHINGLE, THRESHOLD = 5, 0.8
#: 64-bit words of a fingerprint, its segments of 16 bits, and the bits of a segment that documents meet by.
WORDS, SEGMENTS, KEY_BITS = 20, 80, 14
#: Segments of the longest chain that is checked at a meeting, and differing bits a segment that a chain may have.
CHAIN, BUDGET = 8, 4
#: Distinct shingles of a document that also meets others at the segments that begin midway.
FEW = 10
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: Byte counters of the bits of a byte, side by side in a word.
_SPREAD = np.array([sum((b >> k & 1) << 8 * k for k in range(8)) for b in range(256)], np.uint64)


def document_codes(texts: pa.Array, width: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes of all shingles, one document after another, n+1 bounds, and an identifier of each word sequence."""
    data, offsets = text_buffer(pc.utf8_lower(texts))
    starts, ends, row = word_spans(data, offsets)
    words = span_hashes(data, starts, ends)
    heads = row_bounds(row, len(texts))
    sizes = np.diff(heads)
    placed = mix64(words + (np.arange(len(words)) - heads[:-1][row]).astype(np.uint64) * _ODD)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(placed, dtype=np.uint64)])
    ids = mix64(total[heads[1:]] - total[heads[:-1]] + sizes.astype(np.uint64))
    counts = np.maximum(sizes - width + 1, 1)
    bounds = np.concatenate([[0], np.cumsum(counts)])
    at = np.repeat(heads[:-1] - bounds[:-1], counts) + np.arange(int(bounds[-1]))
    padded = np.concatenate([words, np.zeros(width, np.uint64)])
    code = np.zeros(len(at), np.uint64)
    for k in range(width):
        code = (code ^ padded[at + k]) * _ODD
        code ^= code >> np.uint64(31)
    code = mix64(code)
    short = sizes < width
    code[bounds[:-1][short]] = ids[short]
    return code, bounds, ids


def document_prints(code: np.ndarray, bounds: np.ndarray, words: int = WORDS) -> np.ndarray:
    """A row of 64-bit words for each set of codes: bitwise majorities."""
    sizes = np.diff(bounds)
    parts = -(-sizes // 255)  # what a byte can count
    heads = np.cumsum(parts) - parts
    first = np.repeat(bounds[:-1] - 255 * heads, parts) + 255 * np.arange(int(parts.sum()))
    out = np.zeros((len(sizes), words), np.uint64)
    for w in range(words if len(sizes) else 0):
        octets = mix64(code * _ODD + np.uint64(w + 1)).astype("<u8").view(np.uint8).reshape(-1, 8)
        counts = np.hstack([np.add.reduceat(_SPREAD[octets[:, k]], first).astype("<u8").view(np.uint8).reshape(-1, 8) for k in range(8)])
        ones = np.add.reduceat(counts, heads, axis=0, dtype=np.int64)
        out[:, w] = np.packbits(2 * ones > sizes[:, None], axis=1, bitorder="little").view("<u8").ravel()
    return out


def _marks(width: int):
    """(doc_id, tie, id, number of shingles, fingerprint) of every row; a short document's once more, turned by half a segment."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches):
            code, bounds, ids = document_codes(part.column(2), width)
            sets = sorted_sets(code, bounds)
            prints = document_prints(*sets).astype("<u8")
            turned = np.roll(prints.view(np.uint8), -1, axis=1)
            packed = pa.array([p.tobytes() + (t.tobytes() if few else b"") for p, t, few in zip(prints, turned, np.diff(sets[1]) <= FEW, strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(ids.view(np.int64)), pa.array(np.diff(bounds)), packed], ["doc_id", "tie", "id", "size", "print"])

    return run


def segment_entries(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A key for each segment of each fingerprint (rows of words), and the chain of segments from there, as two words."""
    lanes = np.ascontiguousarray(prints.astype("<u8")).view("<u2")
    keys = np.arange(lanes.shape[1], dtype=np.uint64) << np.uint64(KEY_BITS) | (lanes & np.uint16((1 << KEY_BITS) - 1)).astype(np.uint64)
    around = np.lib.stride_tricks.sliding_window_view(np.hstack([lanes, lanes[:, : CHAIN - 1]]), CHAIN, axis=1)
    return keys.ravel(), np.ascontiguousarray(around).view("<u8").reshape(-1, CHAIN // 4)


def _entries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, id, size, a, b) of every segment of the fingerprints in rows (id, size, print)."""
    length = 8 * WORDS
    for batch in batches:
        for at in range(0, batch.num_rows, 1000):
            part = batch.slice(at, 1000)
            held = part.column(2).to_pylist()
            short = np.flatnonzero([len(p) > length for p in held])
            for turn, some in enumerate((np.arange(len(held)), short)):
                keys, chain = segment_entries(np.frombuffer(b"".join(held[k][turn * length :][:length] for k in some.tolist()), "<u8").reshape(-1, WORDS))
                keys += np.uint64(turn * SEGMENTS << KEY_BITS)
                own = [np.repeat(part.column(k).to_numpy()[some], SEGMENTS) for k in range(2)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (keys.view(np.int64), *own, *(chain[:, k].copy().view(np.int64) for k in range(2)))], ["key", "id", "size", "a", "b"])


def chains_within(differing: np.ndarray) -> np.ndarray:
    """Whether all chains from the first segment stay within their budgets, given the xor of chains as rows of two words."""
    found = np.bitwise_count(differing).sum(1, dtype=np.int64) <= CHAIN * BUDGET
    some = np.flatnonzero(found)
    counts = np.bitwise_count(np.ascontiguousarray(differing[some]).view("<u2"))
    found[some] = (np.cumsum(counts, axis=1, dtype=np.int64) <= BUDGET * np.arange(1, CHAIN + 1)).all(1)
    return found


def _meeting(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(home, key, id) of the buckets to verify, from rows (key, id, size, a, b) that are partitioned by key.

    The home of a bucket is its least document: buckets of one home share most of their documents and are verified together.
    """
    parts = [tuple(c.to_numpy().view(np.uint64) for c in b.columns) for b in batches]
    if parts:
        key, own, size, *chain = (np.concatenate(c) for c in zip(*parts, strict=True))
        order = np.lexsort((own, chain[0], key))
        order = order[near_members(key[order], np.column_stack(chain)[order], chains_within)]
        order = order[np.lexsort((own[order], key[order]))]
        key, own = verification_buckets(key[order], own[order], size[order])
        first, stop = runs(key)
        home = np.repeat(np.minimum.reduceat(own, first), stop - first) if len(key) else own
        yield pa.RecordBatch.from_arrays([pa.array(c.view(np.int64)) for c in (home, key, own)], ["home", "key", "id"])
    release_memory()


def document_groups(docs: DataFrame, *, shingle: int = SHINGLE, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, tie (a hash of all columns) and grp of every row that has a doc_id."""
    spark = docs.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8)
    ship_package(spark)
    own = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long"), row_hash(docs).alias("tie"), text_or_empty().alias("text"))
    marks = written(own.mapInArrow(_marks(shingle), "doc_id long, tie long, id long, size long, print binary"), "document-marks")
    firsts = marks.groupBy("id").agg(F.min(F.struct("doc_id", "tie")).alias("first"), F.first("size").alias("size"), F.first("print").alias("print"))
    firsts = written(firsts, "document-firsts")
    entries = firsts.select("id", "size", "print").mapInArrow(_entries, "key long, id long, size long, a long, b long")
    shared = entries.repartition(tasks, "key").mapInArrow(_meeting, "home long, key long, id long")
    candidates = written(shared.distinct(), "document-candidates")
    wanted = candidates.select("id").distinct().join(firsts, "id").select("id", F.col("first.doc_id").alias("at"), F.col("first.tie").alias("at_tie"))
    texts = own.join(wanted, (F.col("doc_id") == F.col("at")) & (F.col("tie") == F.col("at_tie"))).select("id", "text").dropDuplicates(["id"])
    placed = candidates.join(texts, "id").select("home", "key", "id", "text").repartition(tasks, "home").sortWithinPartitions("home", "key")
    coded = lambda texts: document_codes(pa.array(texts, pa.large_string()), shingle)[:2]
    roots = connected_components(placed.mapInArrow(_verify(threshold, coded), "lo long, hi long"), "document-components")
    return marks.select("doc_id", "tie", "id").join(roots, F.col("id") == F.col("node"), "left").select("doc_id", "tie", F.coalesce("root", "id").alias("grp"))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The rows of `docs`, all columns, without the near copies."""
    return keep_least(docs, document_groups(docs, **options))
