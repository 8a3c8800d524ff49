"""Searches that do the whole job: no component left undivided, no search cut short."""

import random

import pytest

from flowrings.operators import baselines
from flowrings.operators.louvain import RoundLog, detect_communities
from flowrings.params import LouvainParams
from flowrings.queries import search_queries


def test_large_components_are_divided(spark):
    chain = [(3 * g + i, 3 * g + j) for g in range(170) for i, j in ((0, 1), (1, 2), (0, 2))] + [(3 * g + 2, 3 * g + 3) for g in range(169)]
    edges = spark.createDataFrame([(7, a, b) for a, b in chain], "mcs long, src long, dst long")
    got = {r.v: r.comm for r in baselines.edge_betweenness(edges).collect()}
    assert len(got) == 510 and len(set(got.values())) > 10
    assert all(got[3 * g] == got[3 * g + 1] == got[3 * g + 2] for g in range(170))


def test_synchronous_search_in_one_task_equals_rounds(spark):
    rng = random.Random(4)
    pairs = [(8 * g + i, 8 * g + j) for g in range(3) for i in range(8) for j in range(8) if i != j and rng.random() < 0.4] + [(0, 8), (8, 16)]
    edges = spark.createDataFrame([(a, b, 1.0 + (a * 7 + b) % 5) for a, b in pairs], "src long, dst long, w double")
    one, many = RoundLog(), RoundLog()
    p = LouvainParams(weight="w", strategy="sync")
    small, large = ({r.v: r.comm for r in detect_communities(edges, p.but(local_edges=n), log).collect()} for n, log in ((1000, one), (0, many)))
    assert small == large and [r[:5] + r[6:] for r in one.rows] == [r[:5] + r[6:] for r in many.rows]
    assert [r[5] for r in one.rows] == pytest.approx([r[5] for r in many.rows])
    assert {r[-1] for r in one.rows} - {None} <= {"settled", "no gain"}


def test_reached_bounds_are_reported(spark):
    edges = spark.createDataFrame([(v, v + 1, 1.0) for v in range(200)], "src long, dst long, w double")
    log = RoundLog()
    with pytest.warns(UserWarning, match="bound"):
        detect_communities(edges, LouvainParams(weight="w", objective="plain", strategy="sync", max_rounds=1, max_levels=1), log)
    assert [r[-1] for r in log.rows] == ["round bound", "level bound"]


def test_registered_synchronous_searches_stop_by_convergence(spark):
    assert min(search_queries.SYNC["max_rounds"], search_queries.SYNC["max_levels"]) > 100
    rows = search_queries.QUERIES["round_log_relay"](spark, "/root/testdata/sf0.001").collect()
    assert {r.stop for r in rows} - {None} <= {"settled", "no gain"}


def test_comparisons_have_the_synchronous_search(spark):
    runs = search_queries._grid_runs()
    cells = {(r["weight"], r["objective"], r["strategy"]) for r in runs.values() if r["objective"] != "inout"}
    assert len(cells) == 18 and len(runs) == 19
    rows = search_queries.QUERIES["agreement_relay"](spark, "/root/testdata/sf0.001").collect()
    assert [r.search for r in rows] == ["sync", "local"] and all(r.n > 0 for r in rows)
