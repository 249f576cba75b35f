"""Connected components by alternating stars: every node ends up linked to the smallest node of its component.

Each partition first shrinks its own edges to a spanning forest. Then large-star and small-star steps, two
joins each, run until the edges stay the same; a hub's edges are never gathered in one task, as minima are
pre-aggregated and skewed joins are split. Every round is written to the shared folder, so lost executors
recompute one round at most.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def forest(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (smallest node, node) that connect what the edges connect; sweeps of pointer jumping."""
    nodes, packed = np.unique(np.concatenate([low, high]), return_inverse=True)
    a, b = packed[: len(low)], packed[len(low) :]
    root = np.arange(len(nodes))
    while True:
        before = root.copy()
        small = np.minimum(root[a], root[b])
        np.minimum.at(root, root[a], small)
        np.minimum.at(root, root[b], small)
        while True:
            jumped = root[root]
            if (jumped == root).all():
                break
            root = jumped
        if (before == root).all():
            break
    moved = root != np.arange(len(nodes))
    return nodes[root[moved]], nodes[moved]


def _shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    low, high, held = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
    for batch in batches:
        low.append(np.asarray(batch.column(0)))
        high.append(np.asarray(batch.column(1)))
        held += batch.num_rows
        if held > 2_000_000:
            a, b = forest(np.concatenate(low), np.concatenate(high))
            low, high, held = [a], [b], len(a) if len(a) < 1_000_000 else 0
            if not held:  # a forest that stays large is passed on; the stars join it with the rest
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["lo", "hi"])
                low, high = [a[:0]], [b[:0]]
    a, b = forest(np.concatenate(low), np.concatenate(high))
    if len(a):
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["lo", "hi"])


def connected_components(edges: DataFrame, name: str = "components", shrink: bool = True) -> DataFrame:
    """(node, root) for every node of the edges (columns lo, hi of long) but the roots themselves.

    Self-links and repeated edges do no harm; nulls are dropped; without edges the result is empty. Edges whose
    partitions are forests already need no shrinking.
    """
    clean = edges.select(F.least("lo", "hi").cast("long").alias("lo"), F.greatest("lo", "hi").cast("long").alias("hi")).where("lo < hi")
    current = written(clean.mapInArrow(_shrink, "lo long, hi long") if shrink else clean, name)
    mark = lambda e: e.agg(F.count("*"), F.sum(F.xxhash64("lo", "hi").cast("decimal(38,0)"))).first()
    state = mark(current)
    while state[0]:
        both = current.select(F.col("lo").alias("u"), F.col("hi").alias("v")).unionByName(current.select(F.col("hi").alias("u"), F.col("lo").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("at"), F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, F.col("u") == F.col("at")).select(F.col("m").alias("lo"), F.col("v").alias("hi")).where("lo < hi").distinct()
        lowest = large.groupBy("hi").agg(F.min("lo").alias("m")).select(F.col("hi").alias("at"), "m")
        small = large.join(lowest, F.col("hi") == F.col("at"))
        linked = small.select(F.explode(F.array(F.struct(F.col("m").alias("a"), F.col("lo").alias("b")), F.struct(F.col("m").alias("a"), F.col("hi").alias("b")))).alias("e"))
        following = written(linked.select(F.col("e.a").alias("lo"), F.col("e.b").alias("hi")).where("lo < hi").distinct(), name)
        reached = mark(following)
        if reached == state:
            break
        current, state = following, reached
    return current.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
