"""From transfers to a merged graph, its node profiles, its components."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowrings.components import star_components
from flowrings.schema import require_columns
from flowrings.scratch import materialize


def merge_transfers(transfers: DataFrame, *, self_transfers: str = "drop") -> DataFrame:
    """One edge per ordered pair: money and times summed, time point averaged."""
    require_columns(transfers, "src", "dst", "amount", "t_sec")
    rows = transfers.filter("src <> dst") if self_transfers == "drop" else transfers
    return rows.groupBy("src", "dst").agg(
        F.sum("amount").cast("decimal(28,2)").alias("money"), F.count(F.lit(1)).alias("times"), F.avg("t_sec").alias("t")
    )


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("v")).union(edges.select("dst")).distinct()


def vertex_profile(edges: DataFrame, node_time: str = "transfer") -> DataFrame:
    """(v, deg, deg_in, deg_out, money, times, t_in, t_out) from one pass over both ends of the edges.

    Mean times weigh each transfer alike, or each merged edge with ``node_time='edge'``.
    """
    weight = F.col("times") if node_time == "transfer" else F.lit(1)
    end = lambda v, into: F.struct(F.col(v).alias("v"), F.lit(into).alias("into"))
    both = edges.select(F.explode(F.array(end("src", 0), end("dst", 1))).alias("x"), "money", "times", "t", weight.alias("n"))
    both = both.select("x.v", "x.into", "money", "times", "t", "n")
    into, out = F.col("into") == 1, F.col("into") == 0
    mean = lambda side: F.sum(F.when(side, F.col("t") * F.col("n"))) / F.sum(F.when(side, F.col("n")))
    return both.groupBy("v").agg(
        F.count(F.lit(1)).alias("deg"), F.count_if(into).alias("deg_in"), F.count_if(out).alias("deg_out"),
        F.sum("money").cast("decimal(28,2)").alias("money"), F.sum("times").alias("times"), mean(into).alias("t_in"), mean(out).alias("t_out"),
    )


def triplets(edges: DataFrame, vertices: DataFrame, cols: list[str]) -> DataFrame:
    """Edges with the given columns of both ends, as s_<col> and d_<col>."""
    side = lambda key, p: vertices.select(F.col("v").alias(key), *(F.col(c).alias(f"{p}_{c}") for c in cols))
    return edges.join(side("src", "s"), "src").join(side("dst", "d"), "dst")


def subgraph(edges: DataFrame, *, edge_pred: Column | None = None, keep: DataFrame | None = None) -> DataFrame:
    """Edges that satisfy a predicate and, with ``keep`` (v), both of whose ends are kept."""
    out = edges if edge_pred is None else edges.filter(edge_pred)
    if keep is not None:
        for end in ("src", "dst"):
            out = out.join(keep.select(F.col("v").alias(end)), end, "left_semi")
    return out.select(edges.columns)


def drop_isolated_edges(edges: DataFrame, isolation: str = "edge") -> DataFrame:
    """Drop edges both of whose ends touch no other edge; with 'pair' also lone reciprocal pairs."""
    if isolation == "edge":
        ends = edges.select(F.explode(F.array("src", "dst")).alias("v"))
        single = ends.groupBy("v").count().filter("count = 1")
    else:
        both = edges.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("x"))
        single = both.select("x.*").distinct().groupBy("v").count().filter("count = 1")
    mark = lambda end: single.select(F.col("v").alias(end), F.lit(True).alias(f"__{end}"))
    marked = edges.join(mark("src"), "src", "left").join(mark("dst"), "dst", "left")
    return marked.filter("__src IS NULL OR __dst IS NULL").select(edges.columns)


def connected_components(edges: DataFrame, method: str = "star", local_edges: int = 200_000) -> DataFrame:
    """(v, mcs): the least vertex id of the component, by star contraction or by plain label spreading."""
    if method == "star":
        return star_components(edges, local_edges=local_edges).withColumnRenamed("root", "mcs")
    links = edges.select("src", "dst").union(edges.select("dst", "src")).toDF("v", "u").distinct()
    links = materialize(links, "links")
    labels = materialize(links.select("v").distinct().withColumn("mcs", F.col("v")), "labels")
    while True:
        heard = links.join(labels.select(F.col("v").alias("u"), "mcs"), "u").groupBy("v").agg(F.min("mcs").alias("heard"))
        new = materialize(labels.join(heard, "v").select("v", F.least("mcs", "heard").alias("mcs"), (F.col("heard") < F.col("mcs")).alias("moved")), "labels")
        if new.filter("moved").isEmpty():
            return new.drop("moved")
        labels = new.drop("moved")


def component_profile(edges: DataFrame, labels: DataFrame, hub_degree: int = 20) -> DataFrame:
    """(mcs, n_vertices, n_edges, n_hubs): hubs have a degree above ``hub_degree``."""
    degrees = edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("deg"))
    return (
        labels.join(degrees, "v").groupBy("mcs")
        .agg(F.count(F.lit(1)).alias("n_vertices"), F.expr("sum(deg) div 2").alias("n_edges"), F.count_if(F.col("deg") > hub_degree).alias("n_hubs"))
    )


def with_component(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Edges with the component of their ends (both have the same)."""
    return edges.join(labels.select(F.col("v").alias("src"), "mcs"), "src")
