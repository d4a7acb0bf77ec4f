"""Connected components of an edge table: alternating star contractions in DataFrame operations, or one task for few edges."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import checkpointed, frugal

#: Edges of long nodes up to this number (32 MB) are joined by one task, which spares some dozens of shuffles.
ONE_TASK_EDGES = 2_000_000


def _large_star(edges: DataFrame) -> DataFrame:
    """Hang every larger neighbour of a node, and nothing else, on the least node that the node sees."""
    both = edges.union(edges.select("v", "u"))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Hang a node and its smaller neighbours on the least of them. Edges come as u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _one_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Union by least node, with path halving."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for batch in batches:
        for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(u), root(v)
            if a != b:
                parent[max(a, b)] = min(a, b)
    nodes = list(parent)
    if nodes:
        yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([root(x) for x in nodes], pa.int64())], ["node", "component"])


def connected_components(edges: DataFrame, max_rounds: int = 60, one_task_edges: int = 0) -> DataFrame:
    """(node, component) for every node of ``edges`` (u long, v long); a component is named by its least node.

    Minima are combined before they are shuffled and joins may be split by AQE, so a node with very many neighbours
    stays spread. Each round is a checkpoint; rounds grow with the logarithm of the size. Loops and repeated edges
    are harmless; edges with a null end are left out; no edges give no rows. Up to ``one_task_edges`` counted edges, whose
    nodes must be long, go to one task instead; the result is the same.
    """
    now = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"), (F.col("u").isNotNull() & F.col("v").isNotNull()).alias("whole"))
    now = checkpointed(now.where("whole and u <> v").select("u", "v").distinct())

    def mark(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    seen = mark(now)
    if 0 < seen[0] <= one_task_edges:
        return now.repartition(1).mapInArrow(frugal(_one_task), "node long, component long")
    for _ in range(max_rounds):
        if not seen[0]:
            break
        now = checkpointed(_small_star(_large_star(now)))
        after = mark(now)
        if after == seen:
            break
        seen = after
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select("v", "v").distinct())
