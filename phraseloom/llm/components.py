"""Connected components of an edge table by alternating large-star and small-star steps, each step checkpointed.

A table of at most ``FEW`` edges is settled in one task instead, which spares the shuffles of every step.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phraseloom.llm.common import durable


#: Edges that one task takes at once (16 bytes each).
FEW = 1 << 19


def _settled(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every node and the least node of its component: roots hook onto lesser ones, then pointers jump."""
    nodes, place = np.unique(np.concatenate([u, v]), return_inverse=True)
    x, y = place[: len(u)], place[len(u) :]
    label = np.arange(len(nodes))
    while (label[x] != label[y]).any():
        left, right = label[x], label[y]
        np.minimum.at(label, np.maximum(left, right), np.minimum(left, right))
        while (label != label[label]).any():
            label = label[label]
    return nodes, nodes[label]


def _at_once(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [[c.to_numpy(zero_copy_only=False) for c in b.columns] for b in batches if b.num_rows]
    if parts:
        yield pa.record_batch([pa.array(c) for c in _settled(*(np.concatenate(side) for side in zip(*parts, strict=True)))], names=["node", "root"])


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One step on undirected edges stored once as ``(u, v)`` with u > v."""
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))) if large else edges
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    joined = both.join(least, "u")
    if large:
        linked = joined.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        own = least.select("u", F.col("m").alias("v"))
        linked = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(own)
    return linked.where(F.col("u") != F.col("v")).distinct()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(node, root)`` for every node with an edge; root is the least node of its component. ``edges``: ``(a, b)``."""
    now = edges.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now = durable(now)
    if now.count() <= FEW:
        return durable(now.coalesce(1).mapInArrow(_at_once, "node long, root long"))
    state = None
    for _ in range(max_rounds):
        now = durable(_star(_star(now, True), False))
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if tuple(seen) == state:
            break
        state = tuple(seen)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
