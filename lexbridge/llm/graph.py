"""Connected components over an edge table.

Up to a counted bound of edges one task joins them in memory; beyond it, large-star and small-star contractions alternate.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.llm.scratch import Scratch


ONE_TASK_EDGES = 500_000


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Union-find with the smallest node of a set as its root."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while (p := up.setdefault(x, x)) != x:
            up[x] = x = up[p]
        return x

    for batch in batches:
        for a, b in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                up[max(a, b)] = min(a, b)
    if up:
        nodes = list(up)
        yield pa.record_batch([pa.array(nodes, pa.int64()), pa.array([root(x) for x in nodes], pa.int64())], names=["node", "comp"])


def _star(edges: DataFrame, small: bool) -> DataFrame:
    """One contraction. ``edges``: (u, v), u > v, distinct. Every node's neighbours are re-hung on the least node near it."""
    if small:
        near = edges
    else:
        near = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = near.groupBy("u").agg(F.min("v").alias("lo")).select("u", F.least("u", "lo").alias("lo"))
    hung = near.join(least, "u")
    if small:
        moved = hung.where("v != lo").select(F.col("v").alias("u"), F.col("lo").alias("v"))
        return moved.unionByName(least.select("u", F.col("lo").alias("v"))).where("u != v").distinct()
    # the larger neighbours of u move to the least; a smaller one meets u from its own side
    return hung.where("v > u").select(F.col("v").alias("u"), F.col("lo").alias("v")).where("u != v").distinct()


def components(edges: DataFrame, a: str, b: str, scratch: Scratch, name: str) -> DataFrame:
    """(node, comp): each node that has an edge, with the smallest node it reaches.

    Edges stay distributed; only a row count and a checksum reach the driver to see that nothing moved. The
    number of rounds is logarithmic in the longest path.
    """
    e = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u != v").distinct()
    e = scratch.keep(e, f"{name}-0")
    if e.count() <= ONE_TASK_EDGES:
        return scratch.keep(e.coalesce(1).mapInArrow(_joined, "node long, comp long"), name)
    mark, turn = None, 0
    while True:
        turn += 1
        nxt = scratch.keep(_star(_star(e, small=False), small=True), f"{name}-{turn}")
        now = nxt.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        scratch.drop(f"{name}-{turn - 1}")
        e = nxt
        if tuple(now) == mark:
            break
        mark = tuple(now)
    e = scratch.keep(e, name)
    roots = e.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(roots)
