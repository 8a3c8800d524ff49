"""Weights, isolation, components, screening, modularity of a given partition, compression."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.operators import baselines, drilldown, evaluate, graph, modularity, screening, weights
from flowrings.operators.compress import compress
from flowrings.params import SMALL_DATA, LouvainParams, ScreenParams
from flowrings.plans.pipeline import screened_graph
from flowrings.queries.common import (
    BASE, COMPONENTS, EVENT_HOURS, EVENT_WEEK, ISOLATION, PROFILE, SMALL, TO_FINAL, TO_SCREENED, TRADE, event_sql, nations, nodes_sql, relay, relay_base,
    relay_connected, relay_screened, relay_sql, shown, trade_screened, trade_sql, z_sql, TRADE_TO_FINAL,
)
from flowrings.scratch import materialize
from flowrings.sources import ledger


def _components(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    edges = materialize(edges, "edges")
    return edges, materialize(graph.connected_components(edges), "labels")


def _profile(edges: DataFrame, hub_degree: int = 3) -> DataFrame:
    edges, labels = _components(edges)
    return graph.component_profile(edges, labels, hub_degree)


def _event_edges(s, d):
    return graph.drop_isolated_edges(graph.merge_transfers(ledger.event(s, d, EVENT_HOURS)))


def _trade_edges(s, d):
    return graph.merge_transfers(ledger.trade(s, d, TRADE))


def _screen_trade(s, d):
    """The published thresholds on ninety days of trade."""
    return screening.screen_components(_profile(_trade_edges(s, d), 20), ScreenParams())


def _node_weight(s, d):
    e = relay_screened(s, d)
    return shown(e.select("src", "dst", "log_w_b", "log_w_n"))


def _compress(s, d):
    return shown(compress(relay_base(s, d), nations(s, d), "w_b"), 3)


def _q(kind):
    return lambda s, d: shown(modularity.modularity(relay_base(s, d), nations(s, d), kind, "w_b"), 9)


def _curve(curve: DataFrame, y: str) -> DataFrame:
    """A curve with its differences at every integer threshold."""
    return shown(screening.every_threshold(screening.second_difference(curve, y)))


def _regions(s, d) -> tuple[DataFrame, DataFrame]:
    """(v, nation_key) and (nation_key, region)."""
    nation, region = s.read.parquet(f"{d}/nation.parquet"), s.read.parquet(f"{d}/region.parquet")
    places = nation.join(region, nation.n_regionkey == region.r_regionkey).select(F.col("n_nationkey").alias("nation_key"), F.col("r_name").alias("region"))
    return s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("v"), F.col("c_nationkey").alias("nation_key")), places


def _changes(s, d):
    """Components with isolated pairs and without: labels that both partitions have, and those of one only."""
    merged = graph.merge_transfers(ledger.event(s, d, EVENT_HOURS))
    both = [graph.connected_components(materialize(e, "edges")).select("v", F.col("mcs").alias("comm")) for e in (graph.drop_isolated_edges(merged), graph.drop_isolated_edges(merged, "pair"))]
    return evaluate.label_changes(*(materialize(x, "labels") for x in both))


def _thresholds(s, d):
    edges, labels = _components(relay_connected(s, d))
    p = screening.choose_thresholds(edges, labels)
    return s.createDataFrame([(p.v_lo, p.v_hi, p.hub_degree, p.n_hubs)], "v_lo int, v_hi int, hub_degree int, n_hubs int")


#: Thresholds of the rule-based screen that flag some edges of the given tables.
RULE_AMOUNT = 90_000.0

QUERIES = {
    "base_weight_relay": lambda s, d: shown(relay_base(s, d).select("src", "dst", "w_b"), 3),
    "isolation_relay": lambda s, d: relay_connected(s, d).select("src", "dst"),
    "isolation_pair_event": lambda s, d: graph.drop_isolated_edges(graph.merge_transfers(ledger.event(s, d, EVENT_HOURS)), "pair").select("src", "dst"),
    "retention_relay": lambda s, d: shown(evaluate.retention(relay_base(s, d), relay_connected(s, d))),
    "components_relay": lambda s, d: _components(relay_connected(s, d))[1],
    "components_event": lambda s, d: _components(_event_edges(s, d))[1],
    "components_minlabel_event": lambda s, d: graph.connected_components(_event_edges(s, d), "minlabel"),
    "component_profile_relay": lambda s, d: _profile(relay_connected(s, d)),
    "sweep_sizes_relay": lambda s, d: _curve(screening.sweep_sizes(_profile(relay_connected(s, d))), "v_remain"),
    "sweep_mean_size_relay": lambda s, d: _curve(screening.sweep_sizes(_profile(relay_connected(s, d))), "v_avg"),
    "sweep_degrees_trade": lambda s, d: _curve(screening.sweep_degrees(graph.vertex_profile(_trade_edges(s, d))), "v_remain"),
    "sweep_hubs_relay": lambda s, d: _curve(screening.sweep_hub_counts(_profile(relay_connected(s, d))), "m_remain"),
    "choose_thresholds_relay": _thresholds,
    "hubs_trade": lambda s, d: screening.hubs(graph.vertex_profile(_trade_edges(s, d)), 20).select("v", "deg"),
    "screen_relay": lambda s, d: screened_graph(relay(s, d), SMALL)[0].select("mcs", "src", "dst"),
    "screen_trade": _screen_trade,
    "screen_size_relay": lambda s, d: evaluate.screen_size(screened_graph(relay(s, d), SMALL)[0]),
    "node_weight_relay": _node_weight,
    "final_weight_relay": lambda s, d: shown(relay_screened(s, d).select("src", "dst", "x_src", "x_dst", "log_w_e")),
    "patterns_relay": lambda s, d: relay_screened(s, d).groupBy(F.element_at(F.split("pattern", ":"), 1).alias("kind")).agg(F.count(F.lit(1)).alias("n")),
    "pattern_census_relay": lambda s, d: weights.pattern_census(relay_screened(s, d)),
    "pagerank_relay": lambda s, d: weights.pagerank(graph.merge_transfers(relay(s, d)), 3).select("v", F.round("rank", 9).alias("rank")),
    "q_plain_relay": _q("plain"),
    "q_flow_relay": _q("flow"),
    "q_inout_relay": _q("inout"),
    "flow_skew_relay": lambda s, d: shown(modularity.flow_skew(relay_base(s, d), "w_b"), 3),
    "compress_relay": _compress,
    "rules_trade": lambda s, d: shown(baselines.rules(_trade_edges(s, d), RULE_AMOUNT, 2)),
    "outliers_trade": lambda s, d: shown(baselines.account_outliers(graph.vertex_profile(_trade_edges(s, d)))),
    "cliques_relay": lambda s, d: baselines.clique_percolation(materialize(relay_connected(s, d), "edges")).select("v", "comm"),
    "cliques_event": lambda s, d: baselines.clique_percolation(materialize(graph.merge_transfers(ledger.event(s, d, EVENT_WEEK)), "edges")).select("v", "comm"),
    "cliques4_event": lambda s, d: baselines.clique_percolation(materialize(graph.merge_transfers(ledger.event(s, d, EVENT_WEEK)), "edges"), 4).select("v", "comm"),
    "final_weight_trade": lambda s, d: shown(trade_screened(s, d).select("src", "dst", "x_src", "x_dst", "log_w_b", "log_w_n", "log_w_e")),
    "dropped_edges_relay": lambda s, d: evaluate.dropped_edges(relay_base(s, d), relay_connected(s, d)).select("src", "dst"),
    "label_changes_event": _changes,
    "volume_cube_relay": lambda s, d: shown(drilldown.volume_cube(graph.merge_transfers(relay(s, d)), *_regions(s, d))),
}

_COMP = "SELECT v, mcs FROM comp"
_SKEW = """
vs AS (SELECT v, sum(i) AS k_in, sum(o) AS k_out, sum(i) + sum(o) AS k FROM (SELECT dst AS v, w_b AS i, 0.0::DOUBLE AS o FROM ew UNION ALL SELECT src, 0.0::DOUBLE, w_b FROM ew) GROUP BY 1),
sk AS (SELECT *, (k_in - k_out) / k AS delta FROM vs)"""


def _q_sql(kind: str) -> str:
    x, y = {"plain": ("k", "k"), "flow": ("k * exp(delta)", "k * exp(-delta)"), "inout": ("k_in", "4 * k_out")}[kind]
    return f"""WITH {relay_sql()}, {BASE}, {_SKEW},
    m AS (SELECT 2 * sum(w_b) AS m2 FROM ew),
    pen AS (SELECT c_nationkey AS comm, sum({x}) AS x, sum({y}) AS y FROM sk JOIN customer ON c_custkey = v GROUP BY 1),
    inn AS (SELECT a.c_nationkey AS comm, 2 * sum(w_b) AS w FROM ew JOIN customer a ON a.c_custkey = src JOIN customer b ON b.c_custkey = dst WHERE a.c_nationkey = b.c_nationkey GROUP BY 1)
    SELECT '{kind}' AS kind, round(sum(coalesce(w, 0) / m2 - x * y / (m2 * m2)), 9) AS q, count(*) AS communities FROM pen LEFT JOIN inn USING (comm), m"""


def _sweep(histogram: str, sums: str, y: str, extra: str = "") -> str:
    return f"""h AS ({histogram}), grid AS (SELECT unnest(generate_series(0, (SELECT max(x) FROM h))) AS threshold),
    c AS (SELECT threshold, {sums} FROM grid LEFT JOIN h ON h.x > threshold GROUP BY 1), c2 AS (SELECT *{extra} FROM c)
    SELECT *, CAST(round(lead({y}) OVER w - {y}, 6) AS DOUBLE) AS d1, CAST(round(lead({y}) OVER w - 2 * {y} + lag({y}) OVER w, 6) AS DOUBLE) AS d2 FROM c2 WINDOW w AS (ORDER BY threshold)"""


_TO_PROFILE = f"WITH RECURSIVE {relay_sql()}, {BASE}, {ISOLATION}, {COMPONENTS}, {PROFILE}"
_SIZES = ("SELECT n_vertices AS x, count(*) AS m FROM prof GROUP BY 1", "CAST(coalesce(sum(m * x), 0) AS BIGINT) AS v_remain, CAST(coalesce(sum(m), 0) AS BIGINT) AS m_remain")
_AVG = ", coalesce(round(v_remain / nullif(CAST(m_remain AS DOUBLE), 0), 6), 0) AS v_avg"
_AVG_RAW = ", coalesce(v_remain / nullif(CAST(m_remain AS DOUBLE), 0), 0) AS v_avg"

ORACLES = {
    "base_weight_relay": f"WITH {relay_sql()}, {BASE} SELECT src, dst, round(w_b, 3) AS w_b FROM ew",
    "isolation_relay": f"WITH {relay_sql()}, {BASE}, {ISOLATION} SELECT src, dst FROM k",
    "isolation_pair_event": f"""WITH {event_sql(EVENT_HOURS)}, l AS (SELECT src AS v, dst AS u FROM e UNION SELECT dst, src FROM e), s AS (SELECT v FROM l GROUP BY 1 HAVING count(*) = 1)
        SELECT src, dst FROM e WHERE NOT (src IN (SELECT v FROM s) AND dst IN (SELECT v FROM s))""",
    "retention_relay": f"""WITH {relay_sql()}, {BASE}, {ISOLATION}, a AS (SELECT count(*) AS n FROM ew), b AS (SELECT count(*) AS n FROM k),
        va AS (SELECT count(DISTINCT v) AS n FROM ends), vb AS (SELECT count(DISTINCT v) AS n FROM (SELECT src AS v FROM k UNION ALL SELECT dst FROM k))
        SELECT a.n AS e_before, b.n AS e_after, va.n AS v_before, vb.n AS v_after, round(b.n / CAST(a.n AS DOUBLE), 6) AS e_share, round(vb.n / CAST(va.n AS DOUBLE), 6) AS v_share FROM a, b, va, vb""",
    "components_relay": f"WITH RECURSIVE {relay_sql()}, {BASE}, {ISOLATION}, {COMPONENTS} {_COMP}",
    "components_event": f"WITH RECURSIVE {event_sql(EVENT_HOURS)}, {BASE}, {ISOLATION}, {COMPONENTS} {_COMP}",
    "component_profile_relay": f"{_TO_PROFILE} SELECT * FROM prof",
    "sweep_sizes_relay": f"{_TO_PROFILE}, {_sweep(*_SIZES, 'v_remain', _AVG)}",
    "sweep_mean_size_relay": f"SELECT * REPLACE (round(v_avg, 6) AS v_avg) FROM ({_TO_PROFILE}, {_sweep(*_SIZES, 'v_avg', _AVG_RAW)})",
    "sweep_degrees_trade": f"WITH {trade_sql()}, {nodes_sql('e')}, {_sweep('SELECT deg AS x, count(*) AS n FROM nd GROUP BY 1', 'CAST(coalesce(sum(n), 0) AS BIGINT) AS v_remain', 'v_remain')}",
    "sweep_hubs_relay": f"{_TO_PROFILE}, {_sweep('SELECT n_hubs AS x, count(*) AS n FROM prof GROUP BY 1', 'CAST(coalesce(sum(n), 0) AS BIGINT) AS m_remain', 'm_remain')}",
    "hubs_trade": f"WITH {trade_sql()}, {nodes_sql('e')} SELECT v, deg FROM nd WHERE deg > 20",
    "screen_relay": f"WITH RECURSIVE {TO_SCREENED} SELECT mcs, src, dst FROM se",
    "screen_trade": f"WITH RECURSIVE {trade_sql()}, k AS (SELECT * FROM e), {COMPONENTS}, {PROFILE.replace('deg > 3', 'deg > 20')} SELECT * FROM prof WHERE n_vertices > 10 AND n_vertices < 2000 AND n_hubs > 7",
    "screen_size_relay": f"WITH RECURSIVE {TO_SCREENED} SELECT (SELECT count(DISTINCT v) FROM (SELECT src AS v FROM se UNION ALL SELECT dst FROM se)) AS vertices, count(*) AS edges, count(DISTINCT mcs) AS components FROM se",
    "node_weight_relay": f"WITH RECURSIVE {TO_FINAL} SELECT src, dst, round(lw, 6) AS log_w_b, round(lwn, 6) AS log_w_n FROM fw",
    "final_weight_relay": f"WITH RECURSIVE {TO_FINAL} SELECT src, dst, round(xs, 6) AS x_src, round(xd, 6) AS x_dst, round(lwn + xs + xd, 6) AS log_w_e FROM fw",
    "patterns_relay": f"WITH RECURSIVE {TO_FINAL} SELECT kind, count(*) AS n FROM fw GROUP BY 1",
    "pattern_census_relay": f"""WITH RECURSIVE {TO_FINAL} SELECT mcs, {', '.join(f"count(*) FILTER (kind = '{x}') AS {x}" for x in ('both', 'gather_then_send', 'gather_before_scatter', 'none'))} FROM fw GROUP BY 1""",
    "pagerank_relay": f"""WITH {relay_sql()}, o AS (SELECT src, sum(times) AS total FROM e GROUP BY 1), s AS (SELECT src, dst, times / CAST(total AS DOUBLE) AS share FROM e JOIN o USING (src)),
        n AS (SELECT src AS v FROM e UNION SELECT dst FROM e), c AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM n), r0 AS (SELECT v, 1 / n AS rank FROM n, c),
        {", ".join(f"r{i} AS (SELECT n.v, 0.15 / max(c.n) + 0.85 * coalesce(sum(share * rank), 0) AS rank FROM n LEFT JOIN (SELECT dst, share, rank FROM s JOIN r{i - 1} ON r{i - 1}.v = s.src) g ON g.dst = n.v, c GROUP BY 1)" for i in (1, 2, 3))}
        SELECT v, round(rank, 9) AS rank FROM r3""",
    "q_plain_relay": _q_sql("plain"),
    "q_flow_relay": _q_sql("flow"),
    "q_inout_relay": _q_sql("inout"),
    "flow_skew_relay": f"WITH {relay_sql()}, {BASE}, {_SKEW} SELECT v, round(k_in, 3) AS k_in, round(k_out, 3) AS k_out, round(k, 3) AS k, round(delta, 3) AS delta FROM sk",
    "compress_relay": f"WITH {relay_sql()}, {BASE} SELECT CAST(a.c_nationkey AS BIGINT) AS src, CAST(b.c_nationkey AS BIGINT) AS dst, round(sum(w_b), 3) AS w FROM ew JOIN customer a ON a.c_custkey = src JOIN customer b ON b.c_custkey = dst GROUP BY 1, 2",
    "rules_trade": f"""WITH {trade_sql()} SELECT src, dst, CAST(money AS DOUBLE) AS money, times, concat_ws(',', CASE WHEN money >= {RULE_AMOUNT} THEN 'amount' END, CASE WHEN times >= 2 THEN 'times' END) AS rule
        FROM e WHERE money >= {RULE_AMOUNT} OR times >= 2""",
    "outliers_trade": f"""WITH {trade_sql()}, {nodes_sql('e')} SELECT * FROM (SELECT v, deg, CAST(money AS DOUBLE) AS money, times,
        round(greatest({z_sql('money', 'nd')}, {z_sql('times', 'nd')}, {z_sql('deg', 'nd')}), 6) AS worst FROM nd) WHERE worst > 3""",
}


def _settled(name: str, histogram: str, sums: str, y: str, extra: str = "") -> str:
    """CTEs ending in ``name`` (x): the first threshold from which the second difference stays small, null if none."""
    curve = _sweep(histogram, sums, y, extra)
    for part in ("h", "grid", "c", "c2"):
        curve = re.sub(rf"\b{part}\b", f"{name}_{part}", curve)
    ctes, _, last = curve.rpartition("\n")
    return f"""{ctes.strip()},
    {name}_d AS ({last.strip()}),
    {name}_w AS (SELECT *, max(abs(d2)) OVER (ORDER BY threshold ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING) AS worst FROM {name}_d),
    {name} AS (SELECT min(threshold) AS x FROM {name}_w WHERE d2 IS NOT NULL AND worst <= 0.01 * (SELECT max(abs(d2)) FROM {name}_d))"""


_HUBS = "SELECT n_hubs AS x, count(*) AS n FROM (SELECT mcs, count(*) FILTER (deg > (SELECT coalesce(x, 20) FROM deg_at)) AS n_hubs FROM comp JOIN d1 USING (v) GROUP BY 1) GROUP BY 1"
_COUNT = lambda n: f"CAST(coalesce(sum(n), 0) AS BIGINT) AS {n}"
ORACLES["choose_thresholds_relay"] = f"""{_TO_PROFILE}, {_settled('lo', *_SIZES, 'v_remain')}, {_settled('hi', *_SIZES, 'v_avg', _AVG_RAW)},
    {_settled('deg_at', 'SELECT deg AS x, count(*) AS n FROM d1 GROUP BY 1', _COUNT('v_remain'), 'v_remain')}, {_settled('hubs_at', _HUBS, _COUNT('m_remain'), 'm_remain')}
    SELECT CAST(coalesce(lo.x, 10) AS INTEGER) AS v_lo, CAST(greatest(coalesce(hi.x, 2000), coalesce(lo.x, 10) + 2) AS INTEGER) AS v_hi,
           CAST(coalesce(deg_at.x, 20) AS INTEGER) AS hub_degree, CAST(coalesce(hubs_at.x, 7) AS INTEGER) AS n_hubs FROM lo, hi, deg_at, hubs_at"""


def _cliques_sql(edges: str, k: int) -> str:
    """Groups of k-cliques linked by k - 1 shared vertices."""
    names = [f"p{i}" for i in range(k)]
    joins = " ".join(f"JOIN pr q{i}_{j} ON q{i}_{j}.a = {'q0_1.a' if i == 0 else f'q0_{i}.b'} AND q{i}_{j}.b = q0_{j}.b" for i in range(1, k) for j in range(i + 1, k))
    heads = "pr q0_1 " + " ".join(f"JOIN pr q0_{j} ON q0_{j}.a = q0_1.a" for j in range(2, k))
    cols = ", ".join(f"{'q0_1.a' if i == 0 else f'q0_{i}.b'} AS {n}" for i, n in enumerate(names))
    return f"""{edges}, pr AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM ke WHERE src <> dst),
    cl AS (SELECT row_number() OVER (ORDER BY {', '.join(names)}) AS id, {', '.join(names)} FROM (SELECT {cols} FROM {heads} {joins})),
    mem AS (SELECT id, unnest([{', '.join(names)}]) AS v FROM cl),
    nb AS (SELECT x.id AS a, y.id AS b FROM mem x JOIN mem y ON x.v = y.v GROUP BY 1, 2 HAVING count(*) >= {k - 1}),
    cr AS (SELECT DISTINCT a AS id, a AS r FROM nb UNION SELECT nb.b, cr.r FROM cr JOIN nb ON nb.a = cr.id WHERE cr.r < nb.b),
    rt AS (SELECT id, min(r) AS r FROM cr GROUP BY 1), gr AS (SELECT DISTINCT r, v FROM mem JOIN rt USING (id)), nm AS (SELECT r, min(v) AS comm FROM gr GROUP BY 1)
    SELECT v, comm FROM gr JOIN nm USING (r)"""


_RELAY_K = f"WITH RECURSIVE {relay_sql()}, {BASE}, {ISOLATION}, ke AS (SELECT * FROM k)"
_EVENT_K = f"WITH RECURSIVE {event_sql(EVENT_WEEK)}, ke AS (SELECT * FROM e)"
_PAIRED = "l AS (SELECT src AS v, dst AS u FROM e UNION SELECT dst, src FROM e), s1 AS (SELECT v FROM l GROUP BY 1 HAVING count(*) = 1)"
ORACLES |= {
    "cliques_relay": _cliques_sql(_RELAY_K, 3),
    "cliques_event": _cliques_sql(_EVENT_K, 3),
    "cliques4_event": _cliques_sql(_EVENT_K, 4),
    "final_weight_trade": f"WITH RECURSIVE {TRADE_TO_FINAL} SELECT src, dst, round(xs, 6) AS x_src, round(xd, 6) AS x_dst, round(lw, 6) AS log_w_b, round(lwn, 6) AS log_w_n, round(lwn + xs + xd, 6) AS log_w_e FROM fw",
    "dropped_edges_relay": f"WITH {relay_sql()}, {BASE}, {ISOLATION} SELECT src, dst FROM ew EXCEPT ALL SELECT src, dst FROM k",
    "label_changes_event": f"""WITH RECURSIVE {event_sql(EVENT_HOURS)}, {BASE}, {ISOLATION}, {COMPONENTS}, {_PAIRED},
        fewer AS (SELECT src, dst FROM e WHERE NOT (src IN (SELECT v FROM s1) AND dst IN (SELECT v FROM s1))), kept_v AS (SELECT src AS v FROM fewer UNION SELECT dst FROM fewer)
        SELECT v, mcs AS comm, CASE WHEN v IN (SELECT v FROM kept_v) THEN 'both' ELSE 'first' END AS side FROM comp""",
    "volume_cube_relay": f"""WITH {relay_sql()}, r AS (SELECT c_custkey AS v, r_name AS region FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)
        SELECT a.region AS payer, b.region AS payee, count(*) AS edges, CAST(sum(money) AS DOUBLE) AS money FROM e JOIN r a ON a.v = src JOIN r b ON b.v = dst GROUP BY CUBE (a.region, b.region)""",
}
ORACLES["components_minlabel_event"] = ORACLES["components_event"]
