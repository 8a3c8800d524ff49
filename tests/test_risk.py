"""Entropy, scores, levels, measures, baselines, planted rings."""

import random

import pytest
from pyspark.sql import functions as F

from flowrings.operators import baselines, drilldown, evaluate, risk
from flowrings.params import SMALL_DATA, LouvainParams, Period, ScreenParams
from flowrings.plans.pipeline import Settings, detect_rings, plan
from flowrings.sources.planted import planted, planted_truth


def one_community(spark, times):
    t = spark.createDataFrame([(1, 2, float(x)) for x in times], "src long, dst long, t_sec double")
    return t, spark.createDataFrame([(1, 1), (2, 1)], "v long, comm long")


def test_entropy(spark):
    # mean 10: gaps 0, 0, 10, 10 -> two halves; all gaps 0 -> 0 bits
    assert risk.time_entropy(*one_community(spark, [10, 10, 0, 20]), 14.0, 7).first().h == pytest.approx(1.0)
    assert risk.time_entropy(*one_community(spark, [3, 3, 3]), 14.0, 7).first().h == 0.0
    assert risk.time_entropy(*one_community(spark, [10, 10, 4, 16, 0, 20, 10, 10]), 30.0, [5.0, 8.0]).first().h == pytest.approx(1.5)


def test_levels(spark):
    scores = spark.createDataFrame([(i, float(i)) for i in range(100)], "comm long, psi double")
    got = {r.level: r.n for r in risk.risk_levels(scores).groupBy("level").agg(F.count("*").alias("n")).collect()}
    assert got == {1: 5, 2: 5, 3: 10, 0: 80}
    assert risk.risk_levels(scores, exact=False).filter("level = 1").count() in (5, 6)


def test_no_spread_scores_one(spark):
    f = spark.createDataFrame([(1, 2, 1, 5.0, 1.0, 0.0), (2, 2, 1, 5.0, 1.0, 0.0)], "comm long, v long, e long, m double, d double, h double")
    assert [r.psi for r in risk.risk_scores(f).collect()] == [1, 1]


def test_curve_and_turning_point(spark):
    s = spark.createDataFrame([(1, 100.0), (2, 50.0), (3, 10.0), (4, 9.9), (5, 9.8)], "comm long, psi double")
    curve = risk.risk_curve(s)
    assert [r.comm for r in curve.orderBy("rank").collect()] == [1, 2, 3, 4, 5]
    assert risk.turning_point(curve) == 3


def test_ranks_by_range_equal_one_window(spark):
    """Ties that span ranges, a tie of half of all communities, one community, none."""
    rng = random.Random(6)
    cases = [[rng.choice([1.0, 2.0, 5.0, rng.random()]) for _ in range(300)], [3.0] * 150 + [float(i) for i in range(150)], [4.0], [2.0, 2.0], [float(i % 3) for i in range(50)]]
    for psi in cases:
        s = spark.createDataFrame([(i * 7 % 1009, x) for i, x in enumerate(psi)], "comm long, psi double")
        show = lambda df, *cols: sorted((r.comm, *(None if r[c] is None else round(r[c], 12) for c in cols)) for r in df.collect())
        assert show(risk.risk_curve(s, 0), "psi", "rank", "slope") == show(risk.risk_curve(s), "psi", "rank", "slope")
        assert show(risk.risk_levels(s, one_task=0), "pct", "level") == show(risk.risk_levels(s), "pct", "level")
    assert risk.risk_curve(s.limit(0), 0).count() == 0 and risk.risk_levels(s.limit(0), one_task=0).count() == 0


def test_scores_of_many_communities_stay_finite(spark):
    f = spark.range(400_000).select(F.col("id").alias("comm"), *(F.when(F.col("id") == 3, 1e9).otherwise(1.0).alias(c) for c in "vemdh"))
    row = risk.risk_scores(f).agg(F.max("psi").alias("top"), F.max_by("comm", "psi").alias("comm"), F.count_if(F.isnan("psi")).alias("nan")).first()
    assert 1e100 < row.top < 1e150 and row.comm == 3 and row.nan == 0


def test_degrees_of_the_whole_graph(spark):
    e = spark.createDataFrame([(1, 2, 5.0, 1, 0.0), (2, 3, 5.0, 1, 0.0), (3, 1, 5.0, 1, 0.0)], "src long, dst long, money double, times long, t double")
    labels = spark.createDataFrame([(1, 1), (2, 1), (3, 3)], "v long, comm long")
    d = lambda scope: {r.comm: r.d for r in risk.community_features(e, labels, scope).collect()}
    assert d("inside") == {1: 1.0, 3: 0.0} and d("graph") == {1: 2.0, 3: 2.0}


def test_coherence_and_comparison_by_hand(spark):
    """Two triangles whose edges differ in time; one partition follows them, one cuts across."""
    rows = [(1, 2, 1.0, 0.0), (2, 3, 1.0, 0.0), (3, 1, 1.0, 0.0), (4, 5, 1.0, 10.0), (5, 6, 1.0, 10.0), (6, 4, 1.0, 10.0), (3, 4, 2.0, 5.0)]
    e = spark.createDataFrame(rows, "src long, dst long, w_b double, t double")
    part = lambda xs: spark.createDataFrame(list(zip(range(1, 7), xs)), "v long, comm long")
    good, cross = part([1, 1, 1, 4, 4, 4]), part([1, 1, 3, 3, 5, 1])
    t = evaluate.time_coherence(e, good).first()
    assert (t.within, t.total, t.edges, t.ratio) == (0.0, 25.0, 6, 0.0)
    s = evaluate.structure_coherence(e, good).first()
    assert (s.communities, s.connected, s.inner_share) == (2, 2, 0.75)
    s = evaluate.structure_coherence(e, cross).first()
    assert (s.communities, s.connected) == (3, 2) and s.inner_share == pytest.approx(3 / 8)  # 6 touches neither 1 nor 2
    got = {(r.a, r.b): (r.n, round(r.share, 6), r.splits) for r in evaluate.compare_partitions(good, cross).collect()}
    assert got == {(1, 1): (2, 0.666667, 2), (1, 3): (1, 0.333333, 2), (4, 3): (1, 0.333333, 3), (4, 5): (1, 0.333333, 3), (4, 1): (1, 0.333333, 3)}


def test_throughput_counts_shuffled_bytes(spark):
    seen = evaluate.throughput(spark, 1000, lambda: spark.range(100_000).groupBy((F.col("id") % 1000).alias("k")).count())
    assert seen["seconds"] > 0 and seen["edges_a_second"] == pytest.approx(1000 / seen["seconds"]) and seen["shuffled_bytes"] > 1000


def test_cube_and_grouping_sets(spark):
    e = spark.createDataFrame([(1, 2, 5.0), (2, 1, 7.0)], "src long, dst long, money double")
    accounts, places = spark.createDataFrame([(1, 10), (2, 20)], "v long, nation_key int"), spark.createDataFrame([(10, "A"), (20, "B")], "nation_key int, region string")
    got = {(r.payer, r.payee): (r.edges, float(r.money)) for r in drilldown.volume_cube(e, accounts, places).collect()}
    assert got[None, None] == (2, 12.0) and got["A", None] == (1, 5.0) and got[None, "A"] == (1, 7.0) and len(got) == 7
    levels = spark.createDataFrame([(1, 1, 2.0), (1, 0, 1.0), (2, 1, 3.0)], "mcs long, level int, psi double")
    sets = {(r.mcs, r.level): (r.communities, r.top_psi) for r in drilldown.level_sets(levels).collect()}
    assert sets == {(1, None): (2, 2.0), (2, None): (1, 3.0), (None, 1): (2, 3.0), (None, 0): (1, 1.0)}


def test_agreement(spark):
    p = lambda xs: spark.createDataFrame(list(enumerate(xs)), "v long, comm long")
    same = evaluate.agreement(p([1, 1, 2, 2]), p([7, 7, 8, 8])).first()
    assert same.nmi == pytest.approx(1) and same.ari == pytest.approx(1)
    cross = evaluate.agreement(p([1, 1, 2, 2]), p([1, 2, 1, 2])).first()
    assert cross.nmi == pytest.approx(0, abs=1e-9) and cross.ari == pytest.approx(-0.5)
    assert evaluate.size_distance(p([1, 1, 2, 2]), p([1, 2, 3, 4])).first().distance == 1


def test_division_and_cliques(spark):
    pairs = [(1, 2), (2, 3), (1, 3), (4, 5), (5, 6), (4, 6), (3, 4)]
    label = baselines.divide(pairs)
    assert label == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 6: 4}
    e = spark.createDataFrame(pairs + [(2, 7), (3, 7)], "src long, dst long")
    got = {(r.v, r.comm) for r in baselines.clique_percolation(e).collect()}
    assert got == {(1, 1), (2, 1), (3, 1), (7, 1), (4, 4), (5, 4), (6, 4)}


def test_hops_match_brute_force(spark):
    rows = [(i % 7, (i * 3 + 1) % 7, float(i * 37 % 500), i) for i in range(60)]
    t = spark.createDataFrame(rows, "src long, dst long, t_sec double, tx_id long")
    got = {(r.in_tx, r.out_tx) for r in drilldown.hop_pairs(t, 40.0).collect()}
    assert got == {(a[3], b[3]) for a in rows for b in rows if a[1] == b[0] and 0 <= b[2] - a[2] <= 40}


def test_planted_rings_rank_high(spark):
    period = Period("2024-01-01", "2024-01-08")
    settings = Settings(screen=ScreenParams(10, 5000, 3, 0), louvain=LouvainParams(strategy="local"))
    report = detect_rings(planted(spark, period, accounts=600, noise=500, rings=6), period, settings)
    risky = report.labels.join(report.risk.filter("level between 1 and 3"), "comm", "left_semi")
    truth = planted_truth(spark, accounts=600, rings=6)
    assert evaluate.precision_recall(risky, truth.select("v")).first().precision > 0.9
    assert risky.join(truth, "v").select("ring").distinct().count() == 6
    assert len(plan(settings)) >= 6


def test_empty_ledger(spark):
    period = Period("2024-01-01", "2024-01-08")
    report = detect_rings(planted(spark, period, noise=5, rings=0).limit(0), period, Settings(screen=SMALL_DATA, louvain=LouvainParams(strategy="local")))
    assert report.risk.count() == 0 and report.suspicious.count() == 0
