"""Connected components of an edge table, distributed, with bounded work in any one task."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

#: Edges that one task contracts at a time.
EDGES_PER_TASK = 500_000


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every node that isn't the least of its component, and that least node; by hooking and pointer jumping."""
    nodes, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = ends[: len(a)], ends[len(a) :]
    root = np.arange(len(nodes))
    while True:
        rx, ry = root[x], root[y]
        if (rx == ry).all():
            break
        np.minimum.at(root, np.maximum(rx, ry), np.minimum(rx, ry))
        while (root[root] != root).any():
            root = root[root]
    own = root != np.arange(len(nodes))
    return nodes[own], nodes[root[own]]


def _local(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held, n = [], 0

    def out() -> pa.RecordBatch:
        t = pa.Table.from_batches(held)
        a, b = forest(t["a"].to_numpy(), t["b"].to_numpy())
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    for batch in batches:
        held.append(batch)
        n += batch.num_rows
        if n >= EDGES_PER_TASK:
            yield out()
            held, n = [], 0
    if n:
        yield out()


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One step of the alternating star contraction; edges run from the larger node a to the smaller node b."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    joined = both.join(least, "a")
    if large:
        moved = joined.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        moved = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    return moved.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def components(edges: DataFrame, per_task: int = EDGES_PER_TASK) -> DataFrame:
    """(a, b) with a any linked node but the least of its component, and b that least node.

    Tasks first contract up to ``per_task`` edges each; where one task holds them all that is the answer, else
    large-star and small-star steps alternate until the edges stay the same.  Each step is checkpointed, so a lost
    executor costs one step at most.  Nodes are longs; loops and repeated edges do no harm.
    """
    edges = edges.select(F.col("a").cast("long"), F.col("b").cast("long")).where("a <> b")
    tasks = -(-max(1, edges.count()) // per_task)
    edges = edges.repartition(tasks).mapInArrow(_local, "a long, b long") if tasks > 1 else edges.coalesce(1).mapInArrow(_local, "a long, b long")
    if tasks == 1:
        return edges
    edges, before = cut(edges), None
    while True:
        edges = cut(_star(_star(edges, True), False))
        now = tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first())
        if now == before:
            return edges
        before = now
