"""Connected components of large undirected graphs by alternating star contractions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.scratch import materialize, release


def star_components(edges: DataFrame, a: str = "src", b: str = "dst", max_rounds: int = 60, local_edges: int = 0) -> DataFrame:
    """(v, root): every vertex of ``edges`` with the least vertex of its component.

    Each round hangs the larger neighbours of every vertex on its least neighbour (large star), then
    the smaller ones (small star).  The number of rounds grows with the logarithm of the longest path,
    not with it, and a vertex of many neighbours is only ever reduced by a minimum, never gathered.
    A graph without edges gives no rows; loops and repeated edges count once.  A graph of at most
    ``local_edges`` edges (counted first) is done by one task instead, which a few megabytes suffice for.
    """
    pairs = edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v"))
    loops = pairs.filter(F.col("u") == F.col("v")).select("u")
    now = materialize(
        pairs.filter(F.col("u") != F.col("v")).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(),
        "star",
    )
    alone = loops.select(F.col("u").alias("v"), F.col("u").alias("root"))
    if local_edges and now.count() <= local_edges:
        found = now.coalesce(1).mapInArrow(_union_find, "v long, root long")
        return found.unionByName(alone).groupBy("v").agg(F.min("root").alias("root"))
    mark = None
    for _ in range(max_rounds):
        before, now = now, materialize(_small_star(_large_star(now)), "star")
        release(before)
        seen = now.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.lit(0).cast("decimal(30,0)"))).first()
        if tuple(seen) == mark:
            break
        mark = tuple(seen)
    else:
        raise RuntimeError(f"components did not settle within {max_rounds} rounds")
    stars = now.select(F.col("u").alias("v"), F.col("v").alias("root"))
    roots = now.select(F.col("v"), F.col("v").alias("root"))
    return stars.unionByName(roots).unionByName(alone).groupBy("v").agg(F.min("root").alias("root"))


def _large_star(now: DataFrame) -> DataFrame:
    """Link each larger neighbour of x to the least of x and its neighbours.

    A large neighbourhood is only joined with its minimum; adaptive execution may split it.
    """
    both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m"))
    least = materialize(least.select("u", F.least("m", "u").alias("m")), "star-least")
    return (
        both.join(least, "u").filter(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        .filter(F.col("u") != F.col("v")).distinct()
    )


def _small_star(now: DataFrame) -> DataFrame:
    """Link each smaller neighbour of x, and x, to the least of them."""
    down = materialize(now, "star-down")
    least = materialize(down.groupBy("u").agg(F.min("v").alias("m")), "star-least")
    linked = down.join(least, "u")
    return (
        linked.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
        .filter(F.col("u") != F.col("v")).distinct()
    )


def _union_find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Roots of all vertices of one partition's edges (u, v)."""
    parts = [np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()]) for b in batches]
    ids, ends = np.unique(np.concatenate(parts, axis=1) if parts else np.empty((2, 0), np.int64), return_inverse=True)
    ends = ends.reshape(2, -1)
    parent = list(range(len(ids)))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    for a, b in ends.T.tolist():
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    roots = np.array([root(i) for i in range(len(ids))], np.int64)
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[roots] if len(ids) else ids)], ["v", "root"])
