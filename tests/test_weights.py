"""Weights and time correction on hand-worked values."""

from math import exp

import pytest
from pyspark.sql import functions as F

from flowrings.functions.stats import scaled_exp, standardise
from flowrings.operators import graph, modularity, weights
from flowrings.params import Period, ScreenParams, WeightParams
from flowrings.plans.pipeline import Settings, weighted_graph
from flowrings.sources.planted import planted


def test_standardise_and_base_weight(spark):
    e = spark.createDataFrame([(1, 100.0, 1), (2, 200.0, 1), (3, 300.0, 2), (4, 400.0, 4)], "src long, money double, times long")
    z = standardise(e, ["money", "times"]).orderBy("src").collect()
    assert [r.z_money for r in z] == pytest.approx([-1.341641, -0.447214, 0.447214, 1.341641], abs=1e-6)
    assert [r.z_times for r in z] == pytest.approx([-0.816497, -0.816497, 0, 1.632993], abs=1e-6)
    w = weights.base_weight(e).orderBy("src").collect()
    assert [r.w_b for r in w] == pytest.approx([0.339912, 0.531605, 1.250579, 4.425207], abs=1e-6)


def test_no_spread_is_zero(spark):
    e = spark.createDataFrame([(1, 5.0), (2, 5.0)], "k long, x double")
    assert [r.z_x for r in standardise(e, ["x"]).collect()] == [0, 0]
    assert [r.z_x for r in standardise(e, ["x"], by="k").collect()] == [0, 0]


def fan(spark, t_mid):
    rows = [(1, 3, 1.0), (2, 3, 3.0), (3, 4, t_mid), (4, 5, 8.0), (4, 6, 9.0)]
    e = spark.createDataFrame([(a, b, 1.0, 1, t) for a, b, t in rows], "src long, dst long, money double, times long, t double")
    e = weights.base_weight(e)
    out = weights.final_weight(e, graph.vertex_profile(e), 10.0, WeightParams()).collect()
    return {(r.src, r.dst): r for r in out}


def test_time_correction(spark):
    got = fan(spark, 6.0)
    mid = got[3, 4]
    assert exp(mid.x_src) == pytest.approx(2.300976, abs=1e-6) and exp(mid.x_dst) == pytest.approx(3.793668, abs=1e-6)
    assert mid.w_e / mid.w_n == pytest.approx(8.729138, abs=1e-5) and mid.pattern == "both:raised"
    assert all(r.w_e == pytest.approx(r.w_n) for k, r in got.items() if k != (3, 4))


def test_demotion_is_capped_and_ties_do_nothing(spark):
    assert exp(fan(spark, 1.5)[3, 4].x_src) == pytest.approx(0.035674, abs=1e-6)
    assert fan(spark, 2.0)[3, 4].x_src == 0.0


def test_equal_nodes_change_nothing(spark):
    e = spark.createDataFrame([(1, 2, 1.0, 1, 0.0), (2, 3, 1.0, 1, 0.0), (3, 1, 1.0, 1, 0.0)], "src long, dst long, money double, times long, t double")
    e = weights.base_weight(e)
    assert all(r.w_n == pytest.approx(r.w_b) for r in weights.final_weight(e, graph.vertex_profile(e), 10.0).collect())


def test_scaled_exponentials_keep_ratios(spark):
    e = spark.createDataFrame([(900.0,), (899.0,), (0.0,)], "lw double")
    got = sorted(r.w for r in e.select(scaled_exp(F.col("lw"), F.lit(900.0)).alias("w")).collect())
    assert got[2] / got[1] == pytest.approx(exp(1)) and got[0] > 0 and got[2] == pytest.approx(exp(300.0))
    assert [r.w for r in e.filter("lw = 0").select(scaled_exp(F.col("lw"), F.lit(9.0)).alias("w")).collect()] == [1.0]


def test_large_ledger_with_one_outlier_stays_finite(spark):
    """A million edges, one of them with nearly all the money: standardised values reach 1,000."""
    e = spark.range(1_000_000).select(
        F.col("id").alias("src"), ((F.col("id") * 7 + 1) % 1_000_000).alias("dst"), F.when(F.col("id") == 5, 1e12).otherwise(10.0 + F.col("id") % 3).alias("money"),
        F.when(F.col("id") == 5, 10**9).otherwise(1).alias("times"), (F.col("id") % 1000).cast("double").alias("t"),
    ).filter("src <> dst")
    w = weights.base_weight(e)
    out = weights.final_weight(w, graph.vertex_profile(e), 1000.0)
    row = out.agg(F.max("log_w_e").alias("log"), F.max("w_b").alias("b"), F.max("w_n").alias("n"), F.max("w_e").alias("e"), F.min("w_b").alias("least"), F.count_if(F.isnan("w_e")).alias("nan")).first()
    assert row.log > 1000 and all(0 < x < 1e150 for x in (row.b, row.n, row.e)) and row.nan == 0 and row.least > 0
    part = spark.range(1_000_000).select(F.col("id").alias("v"), (F.col("id") % 10).alias("comm"))
    assert abs(modularity.modularity(w, part, "flow", "w_b").first().q) < 10


def test_clipped_values(spark):
    e = spark.createDataFrame([(i, 1.0 if i else 1000.0, 1) for i in range(100)], "src long, money double, times long")
    free, clipped = (weights.base_weight(e, WeightParams(z_cap=c)).agg(F.max("log_w_b")).first()[0] for c in (None, 3.0))
    assert free == pytest.approx(0.5 * 99**0.5) and clipped == 1.5


def test_node_scope_and_weight_scope(spark):
    """Standardised over the merged graph or over what was screened: the same edges, other weights."""
    period = Period("2024-01-01", "2024-01-08")
    rows = planted(spark, period, accounts=300, noise=300, rings=3)
    screen = ScreenParams(10, 5000, 3, 0)
    got = {}
    for scope, nodes in (("merged", "screened"), ("screened", "screened"), ("merged", "merged")):
        edges, _ = weighted_graph(rows, period, Settings(screen=screen, weight=WeightParams(scope=scope, node_scope=nodes)))
        got[scope, nodes] = {(r.src, r.dst): (r.log_w_b, r.log_w_n) for r in edges.collect()}
    base = got["merged", "screened"]
    assert base and all(x.keys() == base.keys() for x in got.values())
    mean = lambda x: sum(v[0] for v in x.values()) / len(x)
    assert mean(got["screened", "screened"]) == pytest.approx(0, abs=1e-9) and abs(mean(base)) > 1e-6
    assert all(got["merged", "merged"][k][0] == v[0] for k, v in base.items()) and any(got["merged", "merged"][k][1] != pytest.approx(v[1]) for k, v in base.items())
