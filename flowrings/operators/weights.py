"""Edge weights: volume, importance of the ends, order of money coming in and going out.

Weights are products of exponentials, so their logarithms are added up and kept (log_w_*).  Both
modularities are invariant to scaling all weights, so where logarithms could exceed ``LARGEST_LOG`` (a
standardised value reaches the square root of the number of rows) all weights of a column are divided by
one constant before they overflow; below it they are the plain exponentials.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowrings.functions.stats import scaled_exp, share_bound, share_sum, standardise
from flowrings.operators.graph import triplets
from flowrings.params import WeightParams


def base_weight(edges: DataFrame, params: WeightParams = WeightParams()) -> DataFrame:
    """Add w_b = exp of the share-weighted standardised money and times, and log_w_b."""
    z = standardise(edges, ["money", "times"], cap=params.z_cap, tops=True).withColumn("log_w_b", share_sum(params.edge_shares.of))
    return z.withColumn("w_b", scaled_exp(F.col("log_w_b"), share_bound(params.edge_shares.of))).drop("z_money", "z_times", "top_money", "top_times")


def node_factor(vertices: DataFrame, params: WeightParams = WeightParams()) -> DataFrame:
    """Add sigma = exp of the share-weighted standardised money, times and degree, log_sigma and its bound top_sigma."""
    z = standardise(vertices, ["money", "times", "deg"], cap=params.z_cap, tops=True).withColumn("log_sigma", share_sum(params.node_shares.of))
    z = z.withColumn("top_sigma", share_bound(params.node_shares.of))
    return z.withColumn("sigma", scaled_exp(F.col("log_sigma"), F.col("top_sigma"))).drop(*(f"{p}_{c}" for p in ("z", "top") for c in ("money", "times", "deg")))


def imbalance(vertices: DataFrame) -> DataFrame:
    """Add beta = (deg_in - deg_out) / (deg_in + deg_out), between -1 and 1."""
    return vertices.withColumn("beta", (F.col("deg_in") - F.col("deg_out")) / (F.col("deg_in") + F.col("deg_out")))


def _exponent(beta: Column, applies: Column, gap: Column, seconds: float, cap: float | None) -> Column:
    """beta times tau, where tau is the period over the time gap; 0 where the pattern does not apply or the gap is 0."""
    tau = F.lit(float(seconds)) / F.when(gap != 0, gap)
    if cap is not None:
        tau = F.greatest(F.lit(-cap), F.least(F.lit(cap), tau))
    return F.coalesce(F.when(applies & (gap != 0), beta * tau), F.lit(0.0))


def source_factor(seconds: float, cap: float | None = 10.0) -> Column:
    """log theta of the payer: it gathers more than it sends (beta > 0) and this edge goes out after its mean time in."""
    return _exponent(F.col("s_beta"), F.col("s_beta") > 0, F.col("t") - F.col("s_t_in"), seconds, cap)


def target_factor(seconds: float, cap: float | None = 10.0) -> Column:
    """log theta of the payee: it scatters more than it gathers (beta < 0) and this edge comes in before its mean time out."""
    return _exponent(F.col("d_beta"), F.col("d_beta") < 0, F.col("t") - F.col("d_t_out"), seconds, cap)


def final_weight(edges: DataFrame, vertices: DataFrame, seconds: float, params: WeightParams = WeightParams()) -> DataFrame:
    """Add w_n (base times both node factors) and w_e (with both time factors), their logs and the exponents.

    One triplet view serves both: the edges are joined with their ends once.  ``vertices`` is a node
    profile of the graph that node values are standardised over.
    """
    nodes = imbalance(node_factor(vertices, params))
    t = triplets(edges, nodes, ["log_sigma", "beta", "t_in", "t_out", "top_sigma"])
    t = t.withColumn("log_w_n", F.col("log_w_b") + F.col("s_log_sigma") + F.col("d_log_sigma"))
    t = t.withColumn("x_src", source_factor(seconds, params.tau_cap)).withColumn("x_dst", target_factor(seconds, params.tau_cap))
    t = t.withColumn("log_w_e", F.col("log_w_n") + F.col("x_src") + F.col("x_dst"))
    t = t.withColumn("pattern", pattern_label()).crossJoin(F.broadcast(edges.agg(F.max("log_w_b").alias("__top_b"))))
    top_n = F.col("__top_b") + 2 * F.col("s_top_sigma")
    if params.tau_cap is None:  # literal time factors have no bound but their own maximum
        t = t.crossJoin(F.broadcast(t.agg(F.max(F.col("x_src") + F.col("x_dst")).alias("__top_x"))))
    top_x = F.col("__top_x") if params.tau_cap is None else F.lit(2.0 * params.tau_cap)
    w_n, w_e = scaled_exp(F.col("log_w_n"), top_n), scaled_exp(F.col("log_w_e"), top_n + top_x)
    return t.select(*edges.columns, "log_w_n", w_n.alias("w_n"), "x_src", "x_dst", "log_w_e", w_e.alias("w_e"), "pattern")


def pattern_label() -> Column:
    """Which patterns the edge's ends follow, and whether the correction raised or lowered the weight."""
    gather, scatter = F.col("s_beta") > 0, F.col("d_beta") < 0
    name = F.when(gather & scatter, "both").when(gather, "gather_then_send").when(scatter, "gather_before_scatter").otherwise("none")
    change = F.col("x_src") + F.col("x_dst")
    return F.concat_ws(":", name, F.when(change > 0, "raised").when(change < 0, "lowered").otherwise("same"))


def pattern_census(edges: DataFrame, by: str = "mcs") -> DataFrame:
    """Edges by pattern, one row per component."""
    kinds = ["both", "gather_then_send", "gather_before_scatter", "none"]
    kind = F.element_at(F.split("pattern", ":"), 1)
    counted = edges.withColumn("kind", kind).groupBy(by).pivot("kind", kinds).count()
    return counted.select(by, *(F.coalesce(F.col(k), F.lit(0)).alias(k) for k in kinds))


def pagerank(edges: DataFrame, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """(v, rank): the importance that node correction was inspired by, for comparison."""
    from flowrings.operators.graph import vertices_of
    from flowrings.scratch import materialize

    out = edges.groupBy("src").agg(F.sum("times").alias("total"))
    share = materialize(edges.join(out, "src").select("src", "dst", (F.col("times") / F.col("total")).alias("share")), "rank-shares")
    nodes = materialize(vertices_of(edges), "rank-nodes")
    n = nodes.count()
    ranks = nodes.withColumn("rank", F.lit(1.0 / max(1, n)))
    for _ in range(rounds):
        got = share.join(ranks.withColumnRenamed("v", "src"), "src").groupBy(F.col("dst").alias("v")).agg(F.sum(F.col("rank") * F.col("share")).alias("got"))
        ranks = materialize(nodes.join(got, "v", "left").select("v", (F.lit((1 - damping) / max(1, n)) + damping * F.coalesce("got", F.lit(0.0))).alias("rank")), "ranks")
    return ranks
