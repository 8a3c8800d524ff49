"""Community searches, rounds, repairs, baselines, comparisons."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.operators import baselines, evaluate
from flowrings.operators.louvain import RoundLog, detect_communities, detect_levels, parallel_round, rounds, singletons, unfold
from flowrings.operators.modularity import prepare
from flowrings.operators.repairs import follow_moves, undo_swaps
from flowrings.params import LouvainParams, Period
from flowrings.plans.pipeline import detect_rings
from flowrings.queries.common import SMALL, SPREAD, TO_FINAL, TRADE, TRADE_TO_FINAL, relay_screened, trade_screened
from flowrings.scratch import materialize
from flowrings.sources import ledger
from flowrings.sources.planted import planted, planted_truth


#: Synchronous rounds until convergence: bounds far beyond it, whose reaching is logged and warned of.
SYNC = dict(strategy="sync", max_rounds=1000, max_levels=1000)
STRATEGIES = {"serial": dict(strategy="serial"), "local": dict(strategy="local"), "sync": SYNC}


def _round(spark, sf_dir, kind: str, weight: str) -> DataFrame:
    """One synchronous round from singletons."""
    p = prepare(relay_screened(spark, sf_dir), weight, kind)
    return parallel_round(p, singletons(p.state), LouvainParams(objective=kind, weight=weight)).select("v", "new", F.round("gain", 9).alias("gain"))


def _repair(spark, sf_dir) -> DataFrame:
    p = prepare(relay_screened(spark, sf_dir), "w_e", "flow")
    moves = materialize(parallel_round(p, singletons(p.state)).select("v", "old", "new"), "moves")
    return follow_moves(materialize(undo_swaps(moves), "moves"), "closure").select("v", "new")


def _two_rounds(load, kind: str, weight: str):
    """Labels after two synchronous rounds with both repairs."""
    return lambda s, d: rounds(prepare(load(s, d), weight, kind), LouvainParams(objective=kind, weight=weight), 2)


def _search(load=relay_screened, **changes):
    return lambda s, d: detect_communities(load(s, d), LouvainParams().but(**changes))


def _dendrogram(s, d):
    return unfold(detect_levels(relay_screened(s, d), LouvainParams(strategy="local"))).select("v", "path", "comm")


def _round_log(s, d, load=relay_screened, **changes):
    log = RoundLog()
    detect_communities(load(s, d), LouvainParams(**SYNC).but(**changes), log)
    return s.createDataFrame(log.rows, "level int, round int, moves bigint, swaps bigint, followed bigint, q double, stop string")


def _grid_runs() -> dict[str, dict]:
    """3 weights x 2 objectives x {serial, local, sync}, and the rejected penalty; an objective's own weight is not named."""
    named = {"plain": {"w_b": "", "w_n": "_node", "w_e": "_final"}, "flow": {"w_b": "_base", "w_n": "_node", "w_e": ""}}
    runs = {f"{name}_{kind}{suffix}": dict(objective=kind, weight=w) | how for name, how in STRATEGIES.items() for kind, by in named.items() for w, suffix in by.items()}
    return runs | {"local_inout": dict(objective="inout", weight="w_e", strategy="local")}


def _stack(frames: list[DataFrame], label: str) -> DataFrame:
    """All rows; each frame is computed by itself, so that the plan stays small."""
    out = None
    for rows in frames:
        rows = materialize(rows, label)
        out = rows if out is None else out.unionByName(rows)
    return out


def _grid(s, d, load=relay_screened):
    """Communities and all four modularities of each search: the published comparison and the rest of its grid."""
    edges = load(s, d)

    def one(name: str, changes: dict) -> DataFrame:
        labels = materialize(detect_communities(edges, LouvainParams().but(**changes)), "labels")
        return evaluate.both_modularities(edges, labels).select(F.lit(name).alias("search"), "weight", "kind", F.round("q", 9).alias("q"), "communities")

    return _stack([one(*x) for x in _grid_runs().items()], "grid")


def _agreement(s, d, load=relay_screened):
    """The serial search against the synchronous one, and against the serial one by component (equal by construction)."""
    edges = load(s, d)
    a = materialize(baselines.serial_plain(edges), "labels")

    def one(name: str) -> DataFrame:
        b = materialize(baselines.parallel_plain(edges, **STRATEGIES[name]), "labels")
        return evaluate.agreement(a, b).crossJoin(evaluate.size_distance(a, b)).select(F.lit(name).alias("search"), "*")

    return _stack([one(name) for name in ("sync", "local")], "agreement")


def _case_study(s, d, load=relay_screened):
    """The largest screened component: where each plain community went in the direction-aware search, by strategy."""
    edges = load(s, d)
    top = edges.groupBy("mcs").count().orderBy(F.desc("count"), "mcs").limit(1).select("mcs")
    part = materialize(edges.join(F.broadcast(top), "mcs", "left_semi"), "case")

    def one(name: str) -> DataFrame:
        plain = materialize(baselines.parallel_plain(part, **STRATEGIES[name]), "plain")
        flow = materialize(baselines.flow_and_time(part, **STRATEGIES[name]), "flow")
        return evaluate.compare_partitions(plain, flow).select(F.lit(name).alias("search"), "*")

    return _stack([one(name) for name in ("sync", "local")], "case-study")


def _coherence(s, d, load=relay_screened):
    edges = load(s, d)

    def one(name: str, objective: str) -> DataFrame:
        search = baselines.parallel_plain if objective == "plain" else baselines.flow_and_time
        labels = materialize(search(edges, **STRATEGIES[name]), "labels")
        return evaluate.time_coherence(edges, labels).crossJoin(evaluate.structure_coherence(edges, labels)).select(F.lit(f"{name}_{objective}").alias("search"), "*")

    return _stack([one(name, objective) for name in ("sync", "local") for objective in ("plain", "flow")], "coherence")


def _on_trade(run):
    """A comparison on a graph whose weights are spread over its edges."""
    return lambda s, d: run(s, d, trade_screened)


PLANTED = Period("2024-01-01", "2024-01-08")


def _planted(s, d):
    """Ring accounts among the communities of the riskiest levels: precision and recall."""
    found = detect_rings(planted(s, PLANTED), PLANTED, SMALL)
    risky = found.labels.join(found.risk.filter("level between 1 and 3").select("comm"), "comm", "left_semi").select("v")
    truth = planted_truth(s)
    rings = risky.join(truth, "v").agg(F.countDistinct("ring").alias("rings_found"))
    return evaluate.precision_recall(risky, truth.select("v")).crossJoin(rings)


def _found_trade(s, d):
    return detect_rings(ledger.trade(s, d, TRADE), TRADE, SPREAD)


QUERIES = {
    "plain_round_relay": lambda s, d: _round(s, d, "plain", "w_b"),
    "ftl_round_relay": lambda s, d: _round(s, d, "flow", "w_e"),
    "repair_round_relay": _repair,
    "louvain_serial_relay": _search(objective="plain", weight="w_b", strategy="serial"),
    "louvain_plain_relay": _search(objective="plain", weight="w_b", **SYNC),
    "ftl_relay": _search(**SYNC),
    "ftl_local_relay": _search(strategy="local"),
    "ftl_printed_gain_relay": _search(strategy="local", gain="printed"),
    "ftl_recomputed_relay": _search(strategy="local", delta_mode="recomputed"),
    "inout_relay": _search(strategy="local", objective="inout"),
    "dendrogram_relay": _dendrogram,
    "round_log_relay": _round_log,
    "betweenness_relay": lambda s, d: baselines.edge_betweenness(relay_screened(s, d)),
    "ablation_relay": _grid,
    "agreement_relay": _agreement,
    "case_study_relay": _case_study,
    "coherence_relay": _coherence,
    "planted_accuracy": _planted,
    "two_rounds_relay": _two_rounds(relay_screened, "flow", "w_e"),
    "two_rounds_trade": _two_rounds(trade_screened, "flow", "w_e"),
    "two_rounds_plain_trade": _two_rounds(trade_screened, "plain", "w_b"),
    "ftl_undo_relay": _search(swap_rule="undo", **SYNC),
    "louvain_plain_trade": _search(trade_screened, objective="plain", weight="w_b", **SYNC),
    "ftl_trade": _search(trade_screened, **SYNC),
    "round_log_trade": lambda s, d: _round_log(s, d, trade_screened),
    "round_log_undo_trade": lambda s, d: _round_log(s, d, trade_screened, swap_rule="undo"),
    "ablation_trade": _on_trade(_grid),
    "agreement_trade": _on_trade(_agreement),
    "case_study_trade": _on_trade(_case_study),
    "coherence_trade": _on_trade(_coherence),
    "risk_ftl_trade": lambda s, d: _found_trade(s, d).risk,
    "suspicious_ftl_trade": lambda s, d: _found_trade(s, d).suspicious,
}


def _round_sql(kind: str, w: str) -> str:
    """CTE mv (v, new, gain): moves of the first round."""
    x, y = ("k", "k") if kind == "plain" else ("k * exp((ki - ko) / k)", "k * exp(-(ki - ko) / k)")
    return f"""
    vs AS (SELECT v, sum(i) AS ki, sum(o) AS ko, sum(i) + sum(o) AS k FROM (SELECT dst AS v, {w} AS i, 0.0::DOUBLE AS o FROM fw UNION ALL SELECT src, 0.0::DOUBLE, {w} FROM fw) GROUP BY 1),
    st AS (SELECT v, {x} AS x, {y} AS y FROM vs), m AS (SELECT 2 * sum({w}) AS m2 FROM fw),
    ln AS (SELECT v, u, sum(a) AS a FROM (SELECT src AS v, dst AS u, {w} AS a FROM fw UNION ALL SELECT dst, src, {w} FROM fw) GROUP BY 1, 2),
    sc AS (SELECT ln.v, u, round(2 * a / m2 - (p.x * q.y + p.y * q.x) / (m2 * m2), 12) AS score FROM ln JOIN st p ON p.v = ln.v JOIN st q ON q.v = u, m),
    rk AS (SELECT *, row_number() OVER (PARTITION BY v ORDER BY score DESC, u) AS r FROM sc),
    mv AS (SELECT v, u AS new, round(score, 9) AS gain FROM rk WHERE r = 1 AND score > 1e-12)"""


def _further_sql(n: int, before: str) -> str:
    """CTE lb{n} (v, c): labels after one more round from the labels ``before``, both repairs done."""
    return f"""
    tt{n} AS (SELECT c, sum(x) AS all_x, sum(y) AS all_y FROM st JOIN {before} USING (v) GROUP BY 1),
    cd{n} AS (SELECT v, c, sum(a) AS k, bool_or(own) AS own FROM (SELECT ln.v, l.c, a, false AS own FROM ln JOIN {before} l ON l.v = u UNION ALL SELECT v, c, 0, true FROM {before}) GROUP BY 1, 2),
    sc{n} AS (SELECT cd.v, cd.c, own, round(2 * k / m2 - (x * (all_y - CASE WHEN own THEN y ELSE 0 END) + y * (all_x - CASE WHEN own THEN x ELSE 0 END)) / (m2 * m2), 12) AS score
              FROM cd{n} cd JOIN st USING (v) JOIN tt{n} USING (c), m),
    rk{n} AS (SELECT *, row_number() OVER (PARTITION BY v ORDER BY score DESC, c) AS r, max(score) FILTER (own) OVER (PARTITION BY v) AS stay, max(c) FILTER (own) OVER (PARTITION BY v) AS old FROM sc{n}),
    mv{n} AS (SELECT v, old, c AS new FROM rk{n} WHERE r = 1 AND score - stay > 1e-12 AND c <> old),
    ok{n} AS (SELECT * FROM mv{n} a WHERE a.new < a.old OR NOT EXISTS (SELECT 1 FROM mv{n} b WHERE b.old = a.new AND b.new = a.old)),
    ow{n} AS (SELECT old AS label, new AS target FROM ok{n} WHERE v = old),
    wy{n} AS (SELECT label, target AS stop FROM ow{n} UNION SELECT wy{n}.label, ow{n}.target FROM wy{n} JOIN ow{n} ON ow{n}.label = wy{n}.stop),
    lp{n} AS (SELECT label FROM wy{n} WHERE label = stop),
    en{n} AS (SELECT label, coalesce(min(stop) FILTER (stop NOT IN (SELECT label FROM ow{n})), min(stop) FILTER (stop IN (SELECT label FROM lp{n}))) AS target FROM wy{n} GROUP BY 1),
    lb{n} AS (SELECT l.v, coalesce(en{n}.target, ok{n}.new, l.c) AS c FROM {before} l LEFT JOIN ok{n} ON ok{n}.v = l.v LEFT JOIN en{n} ON en{n}.label = ok{n}.new)"""


def _two_rounds_sql(to_final: str, kind: str, w: str) -> str:
    return f"WITH RECURSIVE {to_final}, {_round_sql(kind, w)}, lb0 AS (SELECT v, v AS c FROM st), {_further_sql(1, 'lb0')}, {_further_sql(2, 'lb1')} SELECT v, c AS comm FROM lb2"


ORACLES = {
    "two_rounds_relay": _two_rounds_sql(TO_FINAL, "flow", "w_e"),
    "two_rounds_trade": _two_rounds_sql(TRADE_TO_FINAL, "flow", "w_e"),
    "two_rounds_plain_trade": _two_rounds_sql(TRADE_TO_FINAL, "plain", "w_b"),
    "plain_round_relay": f"WITH RECURSIVE {TO_FINAL}, {_round_sql('plain', 'w_b')} SELECT v, new, gain FROM mv",
    "ftl_round_relay": f"WITH RECURSIVE {TO_FINAL}, {_round_sql('flow', 'w_e')} SELECT v, new, gain FROM mv",
    "repair_round_relay": f"""WITH RECURSIVE {TO_FINAL}, {_round_sql('flow', 'w_e')},
        ok AS (SELECT v, new FROM mv a WHERE NOT EXISTS (SELECT 1 FROM mv b WHERE b.v = a.new AND b.new = a.v)),
        way AS (SELECT v, new AS stop FROM ok UNION SELECT way.v, ok.new FROM way JOIN ok ON ok.v = way.stop),
        loops AS (SELECT v FROM way WHERE v = stop)
        SELECT v, coalesce(min(stop) FILTER (stop NOT IN (SELECT v FROM ok)), min(stop) FILTER (stop IN (SELECT v FROM loops))) AS new FROM way GROUP BY 1""",
}
