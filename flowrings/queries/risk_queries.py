"""Temporal entropy, risk scores, levels, suspicious components.

The partition that SQL can name is component times nation; the last queries rank found communities.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.operators import drilldown, graph, risk
from flowrings.params import RiskParams
from flowrings.plans.pipeline import detect_rings
from flowrings.queries.common import BASE, COMPONENTS, ISOLATION, RELAY, SMALL, TO_FINAL, nations, relay, relay_connected, relay_screened, relay_sql, shown, z_sql
from flowrings.scratch import materialize


def _graph(s, d) -> tuple[DataFrame, DataFrame]:
    """Connected edges, and the partition (v, comm) with comm = 100 * component + nation."""
    edges = materialize(relay_connected(s, d), "edges")
    mcs = graph.connected_components(edges)
    labels = mcs.join(nations(s, d), "v").select("v", (F.col("mcs") * 100 + F.col("comm")).alias("comm"))
    return edges, materialize(labels, "labels")


def _scores(s, d, params: RiskParams = RiskParams()) -> DataFrame:
    edges, labels = _graph(s, d)
    return risk.community_risk(relay(s, d), edges, labels, RELAY.seconds, params).withColumn("psi", F.round("psi", 9))


def _levels(s, d):
    return risk.risk_levels(_scores(s, d)).withColumn("mcs", F.floor(F.col("comm") / 100).cast("bigint"))


def _rollup(s, d):
    _, labels = _graph(s, d)
    accounts = s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("v"), F.col("c_nationkey").alias("nation_key"))
    nation, region = s.read.parquet(f"{d}/nation.parquet"), s.read.parquet(f"{d}/region.parquet")
    places = nation.join(region, nation.n_regionkey == region.r_regionkey).select(F.col("n_nationkey").alias("nation_key"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
    return drilldown.risk_rollup(materialize(_levels(s, d), "levels"), labels, accounts, places)


def _found(s, d):
    return detect_rings(relay(s, d), RELAY, SMALL)


def _report(s, d):
    edges = relay_screened(s, d)
    return risk.report_nodes(edges, edges.select("mcs").distinct(), 5).select("mcs", "v", F.round(F.log("weight"), 6).alias("log_weight"), F.col("rank").cast("bigint").alias("rank"))


QUERIES = {
    "entropy_relay": lambda s, d: shown(risk.time_entropy(relay(s, d), _graph(s, d)[1], RELAY.seconds)),
    "segments_relay": lambda s, d: shown(risk.segment_shares(relay(s, d), _graph(s, d)[1], RELAY.seconds)),
    "features_relay": lambda s, d: shown(risk.community_features(*_graph(s, d))),
    "risk_relay": lambda s, d: shown(_scores(s, d)),
    "risk_low_entropy_relay": lambda s, d: shown(_scores(s, d, RiskParams(entropy_sign=-1)).select("comm", "psi")),
    "risk_curve_relay": lambda s, d: shown(risk.risk_curve(_scores(s, d)).select("comm", "psi", "rank", "slope")),
    "levels_relay": lambda s, d: shown(_levels(s, d).select("comm", "psi", "pct", "level")),
    "suspicious_relay": lambda s, d: shown(risk.suspicious_components(_levels(s, d))),
    "rollup_relay": _rollup,
    "report_nodes_relay": _report,
    "risk_ftl_relay": lambda s, d: _found(s, d).risk,
    "suspicious_ftl_relay": lambda s, d: _found(s, d).suspicious,
}

_PART = f"""WITH RECURSIVE {relay_sql()}, {BASE}, {ISOLATION}, {COMPONENTS},
lb AS (SELECT v, mcs * 100 + c_nationkey AS comm FROM comp JOIN customer ON c_custkey = v),
own AS (SELECT a.comm, t_sec FROM tr JOIN lb a ON a.v = src JOIN lb b ON b.v = dst WHERE a.comm = b.comm),
mt AS (SELECT comm, avg(t_sec) AS mean_t, count(*) AS total FROM own GROUP BY 1),
sg AS (SELECT comm, CAST(least(floor(abs(t_sec - mean_t) / ({RELAY.seconds} / 7)), 6) AS INTEGER) AS segment, count(*) AS n, count(*) / CAST(max(total) AS DOUBLE) AS p FROM own JOIN mt USING (comm) GROUP BY 1, 2),
en AS (SELECT comm, sum(-p * log2(p)) AS h FROM sg GROUP BY 1),
inn AS (SELECT a.comm, count(*) AS e, sum(money) AS m FROM k JOIN lb a ON a.v = src JOIN lb b ON b.v = dst WHERE a.comm = b.comm GROUP BY 1),
ft AS (SELECT comm, v, coalesce(e, 0) AS e, CAST(coalesce(m, 0) AS DOUBLE) AS m, 2 * coalesce(e, 0) / CAST(v AS DOUBLE) AS d, coalesce(h, 0) AS h
       FROM (SELECT comm, count(*) AS v FROM lb GROUP BY 1) LEFT JOIN inn USING (comm) LEFT JOIN en USING (comm))"""
_PSI = lambda sign: ", ".join([f"ps AS (SELECT *, round(exp(({' + '.join(z_sql(c, 'ft') for c in 'vemd')} {sign} {z_sql('h', 'ft')}) / 5), 9) AS psi FROM ft)"])
_LEVELS = "lv AS (SELECT *, CASE WHEN pct >= 0.95 THEN 1 WHEN pct >= 0.90 THEN 2 WHEN pct >= 0.80 THEN 3 ELSE 0 END AS level FROM (SELECT *, percent_rank() OVER (ORDER BY psi) AS pct FROM ps))"

ORACLES = {
    "entropy_relay": f"{_PART} SELECT comm, round(h, 6) AS h FROM en",
    "segments_relay": f"{_PART} SELECT comm, segment, n, round(p, 6) AS p FROM sg",
    "features_relay": f"{_PART} SELECT comm, v, e, m, round(d, 6) AS d FROM ft",
    "risk_relay": f"{_PART}, {_PSI('+')} SELECT comm, v, e, m, round(d, 6) AS d, round(h, 6) AS h, round(psi, 6) AS psi FROM ps",
    "risk_low_entropy_relay": f"{_PART}, {_PSI('-')} SELECT comm, round(psi, 6) AS psi FROM ps",
    "risk_curve_relay": f"{_PART}, {_PSI('+')} SELECT comm, round(psi, 6) AS psi, row_number() OVER w AS rank, round(lead(psi) OVER w - psi, 6) AS slope FROM ps WINDOW w AS (ORDER BY psi DESC, comm)",
    "levels_relay": f"{_PART}, {_PSI('+')}, {_LEVELS} SELECT comm, round(psi, 6) AS psi, round(pct, 6) AS pct, level FROM lv",
    "suspicious_relay": f"{_PART}, {_PSI('+')}, {_LEVELS} SELECT comm // 100 AS mcs, count(*) FILTER (level BETWEEN 1 AND 2) AS n_risky, count(*) AS n_communities, round(max(psi), 6) AS top_psi FROM lv GROUP BY 1 HAVING count(*) FILTER (level BETWEEN 1 AND 2) >= 2",
    "report_nodes_relay": f"""WITH RECURSIVE {TO_FINAL}, w AS (SELECT mcs, v, sum(w_e) AS weight FROM (SELECT mcs, src AS v, w_e FROM fw UNION ALL SELECT mcs, dst, w_e FROM fw) GROUP BY 1, 2),
        r AS (SELECT *, row_number() OVER (PARTITION BY mcs ORDER BY weight DESC, v) AS rank FROM w) SELECT mcs, v, round(ln(weight), 6) AS log_weight, rank FROM r WHERE rank <= 5""",
    "rollup_relay": f"""{_PART}, {_PSI('+')}, {_LEVELS} SELECT r_name AS region, n_name AS nation, level, count(DISTINCT comm) AS communities, count(DISTINCT lb.v) AS accounts
        FROM lv JOIN lb USING (comm) JOIN customer ON c_custkey = lb.v JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name, level)""",
}
