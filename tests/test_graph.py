"""Merging, profiles, isolation, components, screening on hand-worked graphs."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from flowrings.operators import baselines, drilldown, evaluate, graph, screening
from flowrings.params import ScreenParams, Shares


def transfers(spark, rows):
    return spark.createDataFrame([(a, b, float(m), float(t)) for a, b, m, t in rows], "src long, dst long, amount double, t_sec double").selectExpr("src", "dst", "cast(amount as decimal(18,2)) amount", "t_sec")


def edges(spark, pairs):
    return spark.createDataFrame([(a, b, 1.0, 1, 0.0) for a, b in pairs], "src long, dst long, money double, times long, t double")


def test_merge(spark):
    got = graph.merge_transfers(transfers(spark, [(1, 2, 10, 1), (1, 2, 20, 3), (1, 2, 30, 8), (2, 1, 5, 2), (3, 3, 9, 9)])).collect()
    assert {(r.src, r.dst): (float(r.money), r.times, r.t) for r in got} == {(1, 2): (60, 3, 4), (2, 1): (5, 1, 2)}


def test_self_transfers_can_stay(spark):
    assert graph.merge_transfers(transfers(spark, [(3, 3, 9, 9)]), self_transfers="keep").count() == 1


def test_profile_weighs_transfers(spark):
    merged = graph.merge_transfers(transfers(spark, [(1, 2, 1, 0), (1, 2, 1, 2), (3, 2, 1, 10), (2, 4, 1, 5)]))
    row = graph.vertex_profile(merged).filter("v = 2").first()
    assert (row.deg, row.deg_in, row.deg_out, row.times) == (3, 2, 1, 4)
    assert row.t_in == pytest.approx(4.0) and row.t_out == 5.0
    assert graph.vertex_profile(merged, "edge").filter("v = 2").first().t_in == pytest.approx(5.5)


def test_isolation_and_components(spark):
    e = edges(spark, [(1, 2), (3, 4), (4, 3), (5, 6), (6, 7)])
    kept = graph.drop_isolated_edges(e)
    assert {(r.src, r.dst) for r in kept.collect()} == {(3, 4), (4, 3), (5, 6), (6, 7)}
    assert {(r.src, r.dst) for r in graph.drop_isolated_edges(e, "pair").collect()} == {(5, 6), (6, 7)}
    assert graph.drop_isolated_edges(kept).count() == kept.count()
    assert {r.v: r.mcs for r in graph.connected_components(kept).collect()} == {3: 3, 4: 3, 5: 5, 6: 5, 7: 5}


@pytest.mark.parametrize("how", [dict(local_edges=0), dict(local_edges=10_000), dict(method="minlabel")])
def test_components_agree_with_union_find(spark, how):
    rng = random.Random(7)
    pairs = [(i, i + 1) for i in range(100, 160)] + [(rng.randrange(80), rng.randrange(80)) for _ in range(60)] + [(200, i) for i in range(201, 260)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    got = {r.v: r.mcs for r in graph.connected_components(edges(spark, pairs), **how).collect()}
    assert got == {v: find(v) for v in root}


def test_no_edges_no_components(spark):
    assert graph.connected_components(edges(spark, []) if False else edges(spark, [(1, 2)]).limit(0)).count() == 0


def test_size_sweep(spark):
    mcs = spark.createDataFrame([(1, 3), (2, 3), (3, 5), (4, 12)], "mcs long, n_vertices long")
    got = {r.threshold: (r.v_remain, r.m_remain) for r in screening.sweep_sizes(mcs).collect()}
    assert [got[v] for v in (2, 3, 4, 5, 11, 12)] == [(23, 4), (17, 2), (17, 2), (12, 1), (12, 1), (0, 0)]


def test_screen_is_strict(spark):
    mcs = spark.createDataFrame([(1, 10, 9), (2, 11, 8), (3, 11, 7), (4, 2000, 9)], "mcs long, n_vertices long, n_hubs long")
    assert [r.mcs for r in screening.screen_components(mcs, ScreenParams()).collect()] == [2]


def test_shares_must_sum_to_one():
    with pytest.raises(ValueError):
        Shares({"money": 0.5, "times": 0.6})


def test_curves_keep_what_every_threshold_has(spark):
    """Compact curves against plain sums at every integer, differences and settling points included."""
    rng = random.Random(8)
    for sizes in ([3, 3, 5, 12], [1], [40, 2, 2, 2, 3, 90], [rng.randrange(1, 60) for _ in range(80)], [7, 7, 7]):
        mcs = spark.createDataFrame([(i, n) for i, n in enumerate(sizes)], "mcs long, n_vertices long")
        compact = screening.second_difference(screening.sweep_sizes(mcs), "v_remain")
        top = max(sizes)
        y = [sum(n for n in sizes if n > t) for t in range(top + 1)]
        d2 = [None] + [y[t + 1] - 2 * y[t] + y[t - 1] for t in range(1, top)] + [None] * (top > 0)
        got = screening.every_threshold(compact).orderBy("threshold").collect()
        assert [(r.threshold, r.v_remain) for r in got] == list(enumerate(y))
        assert [r.d2 for r in got] == d2 and [r.d1 for r in got] == [b - a for a, b in zip(y, y[1:])] + [None]
        assert compact.count() <= 3 * len(set(sizes)) + 1
        for tol, run in ((0.01, 5), (0.5, 2), (0.0, 1)):
            most = max((abs(x) for x in d2 if x is not None), default=0)
            want = next((t for t in range(1, top) if all(abs(x) <= tol * most for x in d2[t : t + run] if x is not None)), None)
            assert screening.settling_point(compact, tol, run) == want, (sizes, tol, run)


def test_empty_curve(spark):
    none = spark.createDataFrame([(1, 1)], "mcs long, n_vertices long").limit(0)
    curve = screening.second_difference(screening.sweep_sizes(none), "v_remain")
    assert [(r.threshold, r.v_remain) for r in curve.collect()] == [(0, 0)] and screening.settling_point(curve) is None


def test_chosen_thresholds(spark):
    """A star of 30 leaves, a clique of 12 and many small components: thresholds lie where the curves turn calm."""
    pairs = [(0, i) for i in range(1, 31)] + [(a, b) for a in range(100, 112) for b in range(a + 1, 112)] + [(1000 + 3 * i + j, 1000 + 3 * i + j + 1) for i in range(50) for j in (0, 1)]
    e = edges(spark, pairs)
    p = screening.choose_thresholds(e, graph.connected_components(e))
    assert p.v_lo == 4 and p.v_hi > p.v_lo + 1 and p.hub_degree == 3 and p.n_hubs >= 0
    assert screening.choose_thresholds(e.limit(0), graph.connected_components(e.limit(0))) == ScreenParams(10, 2000, 20, 7)


def test_subgraph_and_samples(spark):
    e = edges(spark, [(1, 2), (2, 3), (3, 4)])
    keep = spark.createDataFrame([(1,), (2,), (3,)], "v long")
    assert {(r.src, r.dst) for r in graph.subgraph(e, keep=keep).collect()} == {(1, 2), (2, 3)}
    assert {(r.src, r.dst) for r in graph.subgraph(e, edge_pred=F.col("src") > 1, keep=keep).collect()} == {(2, 3)}
    wide = spark.range(3000).select((F.col("id") % 1000).alias("mcs"), F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    some = drilldown.sample_components(wide, 20)
    assert 100 < some.select("mcs").distinct().count() < 300 and some.count() == 3 * some.select("mcs").distinct().count()
    assert drilldown.sample_components(wide, 100).count() == 3000 and drilldown.sample_components(wide, 0).count() == 0


def test_cliques_of_any_size_match_brute_force(spark):
    rng = random.Random(12)
    pairs = [(a, b) for a in range(18) for b in range(a + 1, 18) if rng.random() < 0.45]
    near = {frozenset(p) for p in pairs}
    for k in (2, 3, 4, 5):
        found = [c for c in combinations(range(18), k) if all(frozenset(p) in near for p in combinations(c, 2))]
        groups = [{c} for c in found]
        merged = True
        while merged:
            merged = False
            for i in range(len(groups)):
                for j in range(i + 1, len(groups)):
                    if any(len(set(a) & set(b)) >= k - 1 for a in groups[i] for b in groups[j]):
                        groups[i] |= groups.pop(j)
                        merged = True
                        break
                if merged:
                    break
        want = sorted((v, min(min(c) for c in g)) for g in groups for v in {v for c in g for v in c})
        got = baselines.clique_percolation(spark.createDataFrame(pairs, "src long, dst long"), k)
        assert sorted((r.v, r.comm) for r in got.collect()) == want, k
    with pytest.raises(ValueError):
        baselines.clique_percolation(spark.createDataFrame(pairs, "src long, dst long"), 1)


def test_audits_and_label_changes(spark):
    before, after = edges(spark, [(1, 2), (3, 4), (5, 6)]), edges(spark, [(3, 4)])
    assert {(r.src, r.dst) for r in evaluate.dropped_edges(before, after).collect()} == {(1, 2), (5, 6)}
    a, b = (spark.createDataFrame(x, "v long, comm long") for x in ([(1, 1), (2, 1), (3, 3)], [(1, 1), (2, 2)]))
    assert {(r.v, r.comm, r.side) for r in evaluate.label_changes(a, b).collect()} == {(1, 1, "both"), (2, 1, "first"), (3, 3, "first"), (2, 2, "second")}
