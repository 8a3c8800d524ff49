"""The graph of communities: inner weight becomes a self edge, weight between communities an edge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def compress(edges: DataFrame, labels: DataFrame, weight: str = "w") -> DataFrame:
    """(src, dst, w) between communities, direction kept."""
    side = lambda end: labels.select(F.col("v").alias(end), F.col("comm").alias(f"c_{end}"))
    both = edges.select("src", "dst", F.col(weight).alias("w")).join(side("src"), "src").join(side("dst"), "dst")
    return both.groupBy(F.col("c_src").alias("src"), F.col("c_dst").alias("dst")).agg(F.sum("w").alias("w"))


def carried_sums(state: DataFrame, labels: DataFrame) -> DataFrame:
    """(v, x, y) of the communities: sums over members, which keep the modularity of the partition."""
    return state.join(labels, "v").groupBy(F.col("comm").alias("v")).agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
