"""Modularities of a partition: undirected, direction-aware and the rejected in-times-out form.

All three have one shape.  With A the symmetric weights (both directions added), W_c the weight inside
a community over ordered pairs, and per-vertex numbers x and y,

    Q = sum over communities of  W_c / 2m  -  X_c Y_c / (2m)^2,     X_c = sum x,  Y_c = sum y,

so the N x N penalty matrix of a community is the product of two sums and is never built.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowrings.scratch import materialize, materialize_observed, release

KINDS = ("plain", "flow", "inout")


def penalty(kind: str) -> tuple[Column, Column]:
    """x and y from the weight sums k, k_in, k_out."""
    k, k_in, k_out = F.col("k"), F.col("k_in"), F.col("k_out")
    if kind == "plain":
        return k, k
    if kind == "flow":
        skew = F.when(k > 0, (k_in - k_out) / k).otherwise(0.0)
        return k * F.exp(skew), k * F.exp(-skew)
    if kind == "inout":
        return k_in, 4 * k_out  # over m^2 instead of (2m)^2
    raise ValueError(f"kind must be one of {KINDS}")


def flow_skew(edges: DataFrame, weight: str) -> DataFrame:
    """(v, k, k_in, k_out, delta): weight sums of each vertex; a self edge counts once on either side."""
    into = edges.select(F.col("dst").alias("v"), F.col(weight).alias("i"), F.lit(0.0).alias("o"))
    out = edges.select(F.col("src").alias("v"), F.lit(0.0).alias("i"), F.col(weight).alias("o"))
    sums = into.unionByName(out).groupBy("v").agg(F.sum("i").alias("k_in"), F.sum("o").alias("k_out"))
    sums = sums.withColumn("k", F.col("k_in") + F.col("k_out"))
    return sums.withColumn("delta", F.when(F.col("k") > 0, (F.col("k_in") - F.col("k_out")) / F.col("k")).otherwise(0.0))


@dataclass
class Prepared:
    """What a search needs: links (v, u, a, x, y of v) in both directions, state (v, x, y), the weight of self
    edges, twice the total weight, the numbers of edges and vertices."""

    links: DataFrame
    state: DataFrame
    loops: float
    two_m: float
    n_edges: int
    n_vertices: int


def prepare(edges: DataFrame, weight: str, kind: str, carried: DataFrame | None = None) -> Prepared:
    """Links and vertex numbers; ``carried`` (v, x, y) takes the place of numbers computed from the edges."""
    w, same = F.col("w"), F.col("src") == F.col("dst")
    own, seen = materialize_observed(
        edges.select("src", "dst", F.col(weight).cast("double").alias("w")).filter("w > 0"), "weighted",
        total=F.coalesce(F.sum("w"), F.lit(0.0)), loops=F.coalesce(F.sum(F.when(same, w)), F.lit(0.0)), n=F.count(F.lit(1)),
    )
    x, y = penalty(kind)
    state = carried if carried is not None else flow_skew(own, "w").select("v", x.alias("x"), y.alias("y"))
    state, sums = materialize_observed(state, "vertex-sums", n=F.count(F.lit(1)))
    both = own.filter("src <> dst").select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("e"), "w")
    links = both.groupBy("e.v", "e.u").agg(F.sum("w").alias("a")).join(state, "v")
    links = materialize(links, "links")
    release(own)
    return Prepared(links, state, seen.get("loops", 0.0), 2 * seen.get("total", 0.0), seen.get("n", 0), sums.get("n", 0))


def modularity(edges: DataFrame, labels: DataFrame, kind: str = "plain", weight: str = "w_b", resolution: float = 1.0) -> DataFrame:
    """One row (kind, q, communities): of the partition ``labels`` (v, comm) on the original graph.

    Vertices without a label form no community and inner edges need both labels.  A graph without
    weight has q 0.
    """
    own = edges.select("src", "dst", F.col(weight).cast("double").alias("w"))
    x, y = penalty(kind)
    sums = flow_skew(own, "w").select("v", x.alias("x"), y.alias("y"))
    side = lambda end: labels.select(F.col("v").alias(end), F.col("comm").alias(f"c_{end}"))
    inner = own.join(side("src"), "src").join(side("dst"), "dst").filter("c_src = c_dst").groupBy(F.col("c_src").alias("comm")).agg((2 * F.sum("w")).alias("inner"))
    parts = sums.join(labels, "v").groupBy("comm").agg(F.sum("x").alias("x"), F.sum("y").alias("y")).join(inner, "comm", "left")
    total = own.agg((2 * F.sum("w")).alias("two_m"))
    two_m = F.col("two_m")
    term = F.coalesce("inner", F.lit(0.0)) / two_m - F.lit(resolution) * F.col("x") * F.col("y") / (two_m * two_m)
    return (
        parts.crossJoin(F.broadcast(total)).filter(two_m > 0)
        .agg(F.coalesce(F.sum(term), F.lit(0.0)).alias("q"), F.count(F.lit(1)).alias("communities"))
        .select(F.lit(kind).alias("kind"), "q", "communities")
    )


def gain(k_c: float, theta: float, two_m: float, form: str = "exact", resolution: float = 1.0) -> float:
    """The change of Q when a lone vertex joins a community: its links to it, and its penalty with it.

    ``exact`` is the difference of the modularity; ``printed`` counts the links once instead of twice,
    which equals half the exact gain at twice the resolution.
    """
    return (2 if form == "exact" else 1) * k_c / two_m - resolution * theta / two_m**2


def theta(x: float, y: float, x_c: float, y_c: float) -> float:
    """The penalty between a vertex and a community, both orders."""
    return x * y_c + y * x_c


def penalty_matrix(k: list[float], delta: list[float]) -> list[list[float]]:
    """The explicit matrix of one community, for checking the factorised form on small graphs."""
    from math import exp

    return [[exp(di - dj) * ki * kj for kj, dj in zip(k, delta)] for ki, di in zip(k, delta)]
