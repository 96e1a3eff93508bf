"""Connected components over an edge DataFrame: forests inside partitions, then alternating stars.

Each partition first reduces its edges to a forest of stars, so partitions hold
one edge a vertex at most.  Edges that fill a single partition of bounded size are
done with that.  Others go through rounds of two grouped passes that shrink every
tree towards its smallest vertex.  Edges are written to the shared checkpoint
folder between rounds, so lineage stays short and a lost executor costs one round.
Nothing but convergence scalars reaches the driver.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import checkpointed

EDGES_PER_PART = 1_000_000


def local_forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vertex, root) for every vertex of the edges (a, b); a tree's root is its smallest vertex."""
    names, index = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v = index[: len(a)], index[len(a) :]
    up = np.arange(len(names))
    while True:
        low, high = np.minimum(up[u], up[v]), np.maximum(up[u], up[v])
        if (low == high).all():
            return names, names[up]
        np.minimum.at(up, high, low)
        while not (up[up] == up).all():
            up = up[up]


def _forests(edges: DataFrame) -> DataFrame:
    """Stars (a, b) of every partition's trees; a root is a star of its own (a = b)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [(batch.column("a").to_numpy(), batch.column("b").to_numpy()) for batch in batches]
        if held:
            vertex, root = local_forest(*(np.concatenate(x) for x in zip(*held)))
            yield pa.RecordBatch.from_arrays([pa.array(vertex), pa.array(root)], ["a", "b"])

    return edges.mapInArrow(run, "a long, b long")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = both.groupBy("a").agg(F.min("b").alias("low")).select("a", F.least("a", "low").alias("low"))
    return both.join(low, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("low").alias("b")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = down.groupBy("a").agg(F.min("b").alias("low"))
    joined = down.join(low, "a")
    links = joined.select(F.col("b").alias("a"), F.col("low").alias("b")).unionByName(joined.select("a", F.col("low").alias("b")))
    return links.where(F.col("a") != F.col("b")).distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60, edges_per_part: int = EDGES_PER_PART) -> DataFrame:
    """(a, b) edges with comparable ids -> (vertex, component): the smallest id reachable.

    Vertices without edges don't appear.  Self loops and nulls are ignored.
    """
    kept = checkpointed(edges.where("a is not null and b is not null and a <> b").select("a", "b"))
    parts = max(1, math.ceil(kept.count() / edges_per_part))
    forests = checkpointed(_forests(kept.coalesce(parts)))
    if parts == 1:
        return forests.select(F.col("a").alias("vertex"), F.col("b").alias("component"))
    now, before = forests.where("a <> b"), None
    for _ in range(max_rounds):
        now = checkpointed(_small_star(_large_star(now)))
        state = tuple(now.agg(F.count("*"), F.coalesce(F.sum(F.hash("a", "b").cast("long")), F.lit(0))).first())
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components did not converge in {max_rounds} rounds")
    roots = now.select(F.col("b").alias("vertex"), F.col("b").alias("component")).distinct()
    return now.select(F.col("a").alias("vertex"), F.col("b").alias("component")).unionByName(roots)
