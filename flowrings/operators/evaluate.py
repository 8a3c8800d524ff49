"""Measures of cost, agreement and coherence."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from flowrings.components import star_components
from flowrings.operators.modularity import modularity
from flowrings.operators.risk import inside


def timed(make: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """The frame and the seconds to build it and run it to a sink that keeps nothing."""
    start = time.perf_counter()
    df = make()
    df.write.format("noop").mode("overwrite").save()
    return df, time.perf_counter() - start


def throughput(spark: SparkSession, edges: int, make: Callable[[], DataFrame]) -> dict[str, float]:
    """Seconds, edges a second and shuffled bytes of building a frame and running it to a sink that keeps nothing."""
    def shuffled() -> int:
        seen = spark.sparkContext._jsc.sc().statusStore().executorList(False)
        return sum(seen.apply(i).totalShuffleWrite() for i in range(seen.size()))

    before = shuffled()
    _, seconds = timed(make)
    return {"seconds": seconds, "edges_a_second": edges / seconds, "shuffled_bytes": shuffled() - before}


def label_changes(a: DataFrame, b: DataFrame) -> DataFrame:
    """(v, comm, side): labels that only one of two partitions has, and those that both have."""
    a, b = (x.select("v", "comm") for x in (a, b))
    parts = [x.withColumn("side", F.lit(n)) for n, x in (("both", a.intersect(b)), ("first", a.exceptAll(b)), ("second", b.exceptAll(a)))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def dropped_edges(before: DataFrame, after: DataFrame) -> DataFrame:
    """The audit of a filter: edges of ``before`` that ``after`` lacks."""
    return before.join(after.select("src", "dst"), ["src", "dst"], "left_anti").select(before.columns)


def retention(before: DataFrame, after: DataFrame) -> DataFrame:
    """One row: edges and vertices before and after a filter, and the shares kept."""
    def size(df: DataFrame, p: str) -> DataFrame:
        ends = df.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.countDistinct("v").alias(f"v_{p}"))
        return df.agg(F.count(F.lit(1)).alias(f"e_{p}")).crossJoin(ends)

    share = lambda x: F.coalesce(F.col(f"{x}_after") / F.when(F.col(f"{x}_before") > 0, F.col(f"{x}_before")), F.lit(0.0)).alias(f"{x}_share")
    return size(before, "before").crossJoin(size(after, "after")).select("e_before", "e_after", "v_before", "v_after", share("e"), share("v"))


def screen_size(edges: DataFrame) -> DataFrame:
    """One row: vertices, edges and components (column mcs) of a screened graph."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.countDistinct("v").alias("vertices"))
    return ends.crossJoin(edges.agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("mcs").alias("components")))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row (n, nmi, ari, a_parts, b_parts) for two partitions (v, comm) of shared vertices.

    NMI is over the mean of both entropies; two partitions into one part each agree fully.
    """
    cells = a.select("v", F.col("comm").alias("a")).join(b.select("v", F.col("comm").alias("b")), "v").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    total = cells.agg(F.sum("n").alias("total"))
    pairs = lambda c: (F.col(c) * (F.col(c) - 1) / 2.0)
    ent = lambda c: F.sum(-(F.col(c) / F.col("total")) * F.log2(F.col(c) / F.col("total")))
    row = lambda g, p: cells.groupBy(g).agg(F.sum("n").alias("s")).crossJoin(F.broadcast(total)).agg(ent("s").alias(f"h_{p}"), F.sum(pairs("s")).alias(f"p_{p}"), F.count(F.lit(1)).alias(f"{p}_parts"))
    joint = cells.crossJoin(F.broadcast(total)).agg(ent("n").alias("h"), F.sum(pairs("n")).alias("p"), F.max("total").alias("n"))
    wide = joint.crossJoin(row("a", "a")).crossJoin(row("b", "b"))
    mutual, mean = F.col("h_a") + F.col("h_b") - F.col("h"), (F.col("h_a") + F.col("h_b")) / 2
    expected = F.when(F.col("n") > 1, F.col("p_a") * F.col("p_b") / pairs("n")).otherwise(0.0)
    top = (F.col("p_a") + F.col("p_b")) / 2 - expected
    return wide.select(
        "n", F.when(mean > 0, mutual / mean).otherwise(1.0).alias("nmi"), F.when(F.abs(top) > 0, (F.col("p") - expected) / top).otherwise(1.0).alias("ari"), "a_parts", "b_parts"
    )


def size_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: half the absolute difference of the shares of communities by size (0 same, 1 disjoint)."""
    def sizes(x: DataFrame, name: str) -> DataFrame:
        h = x.groupBy("comm").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("n"))
        return h.crossJoin(F.broadcast(h.agg(F.sum("n").alias("t")))).select("size", (F.col("n") / F.col("t")).alias(name))

    both = sizes(a, "a").join(sizes(b, "b"), "size", "full")
    return both.agg((F.sum(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)))) / 2).alias("distance"))


def compare_partitions(a: DataFrame, b: DataFrame) -> DataFrame:
    """(a, b, n, share, splits): where each community of ``a`` went in ``b``, largest part first."""
    cells = a.select("v", F.col("comm").alias("a")).join(b.select("v", F.col("comm").alias("b")), "v").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    of_a = Window.partitionBy("a")
    return cells.select("a", "b", "n", (F.col("n") / F.sum("n").over(of_a)).alias("share"), F.count(F.lit(1)).over(of_a).alias("splits"))


def time_coherence(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: variance of edge times within communities over their variance among all inner edges (0: times explained)."""
    inner = inside(edges.select("src", "dst", "t"), labels)
    by = inner.groupBy("comm").agg(F.count(F.lit(1)).alias("n"), F.var_pop("t").alias("var"))
    total = inner.agg(F.var_pop("t").alias("total"), F.count(F.lit(1)).alias("edges"))
    within = by.agg((F.sum(F.col("n") * F.col("var")) / F.sum("n")).alias("within"))
    return within.crossJoin(total).select("within", "total", "edges", F.when(F.col("total") > 0, F.col("within") / F.col("total")).otherwise(0.0).alias("ratio"))


def structure_coherence(edges: DataFrame, labels: DataFrame, weight: str = "w_b") -> DataFrame:
    """One row: communities, how many are connected inside, and the share of weight that is inner."""
    inner = inside(edges.select("src", "dst", weight), labels)
    roots = star_components(inner, local_edges=200_000)
    parts = labels.join(roots, "v", "left").groupBy("comm").agg(F.countDistinct(F.coalesce("root", "v")).alias("parts"))
    weights = inner.agg(F.coalesce(F.sum(weight), F.lit(0.0)).alias("inner")).crossJoin(edges.agg(F.sum(weight).alias("all")))
    return parts.agg(F.count(F.lit(1)).alias("communities"), F.count_if(F.col("parts") == 1).alias("connected")).crossJoin(weights).select("communities", "connected", (F.col("inner") / F.col("all")).alias("inner_share"))


def precision_recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row for two sets of ids (column v): hits, precision, recall."""
    hit = found.select("v").distinct().join(truth.select("v").distinct(), "v", "left_semi").agg(F.count(F.lit(1)).alias("hits"))
    n = lambda df, c: df.agg(F.countDistinct("v").alias(c))
    wide = hit.crossJoin(n(found, "found")).crossJoin(n(truth, "truth"))
    ratio = lambda c: F.coalesce(F.col("hits") / F.when(F.col(c) > 0, F.col(c)), F.lit(0.0))
    return wide.select("hits", "found", "truth", ratio("found").alias("precision"), ratio("truth").alias("recall"))


def both_modularities(edges: DataFrame, labels: DataFrame, weights: tuple[str, ...] = ("w_b", "w_e")) -> DataFrame:
    """(weight, kind, q, communities): a partition under either objective on either weight."""
    out = None
    for w in weights:
        for kind in ("plain", "flow"):
            row = modularity(edges, labels, kind, w).select(F.lit(w).alias("weight"), "kind", "q", "communities")
            out = row if out is None else out.unionByName(row)
    return out
