"""The whole detection: from transfers of a period to ranked communities and suspicious components."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.operators import graph, risk, screening, weights
from flowrings.operators.louvain import RoundLog, detect_communities
from flowrings.params import LouvainParams, Period, RiskParams, ScreenParams, WeightParams
from flowrings.scratch import materialize


@dataclass(frozen=True)
class Settings:
    screen: ScreenParams = ScreenParams()
    weight: WeightParams = WeightParams()
    louvain: LouvainParams = LouvainParams()
    risk: RiskParams = RiskParams()


@dataclass
class RingReport:
    """All frames are lazy except for what loops had to materialise."""

    edges: DataFrame
    mcs: DataFrame
    labels: DataFrame
    risk: DataFrame
    suspicious: DataFrame
    log: RoundLog = field(default_factory=RoundLog)


def plan(settings: Settings) -> list[str]:
    """The stages that ``detect_rings`` will run, in order, with the choices the settings imply."""
    out = ["merge transfers by (src, dst)"]
    if settings.weight.scope == "merged":
        out.append("base weight over the merged graph")
    out.append("drop isolated edges" if settings.screen.v_lo < 2 else "drop isolated edges (the size screen would, too: saves component rounds)")
    out += ["connected components by star contraction", f"screen components: {settings.screen}"]
    if settings.weight.scope == "screened":
        out.append("base weight over the screened graph")
    out.append(f"node and time correction over the {settings.weight.node_scope} graph")
    out.append(f"communities: {settings.louvain.objective} modularity on {settings.louvain.weight}, {settings.louvain.strategy}")
    out.append("risk scores, levels, suspicious components")
    return out


def screened_graph(transfers: DataFrame, settings: Settings, screened: bool = True) -> tuple[DataFrame, DataFrame]:
    """Edges of the kept components with all weights and column mcs, and the components' profile."""
    merged = graph.merge_transfers(transfers)
    if settings.weight.scope == "merged":
        merged = weights.base_weight(merged, settings.weight)
    merged = materialize(merged, "merged-edges")
    connected = materialize(graph.drop_isolated_edges(merged), "connected-edges")
    labels = materialize(graph.connected_components(connected), "component-labels")
    mcs = materialize(graph.component_profile(connected, labels, settings.screen.hub_degree), "components")
    kept = screening.screen_components(mcs, settings.screen) if screened else mcs
    edges = screening.apply_screen(connected, labels, kept)
    if settings.weight.scope == "screened":
        edges = weights.base_weight(edges, settings.weight)
    return materialize(edges, "screened-edges"), kept


def weighted_graph(transfers: DataFrame, period: Period, settings: Settings = Settings(), screened: bool = True) -> tuple[DataFrame, DataFrame]:
    """``screened_graph`` with node and time correction."""
    edges, kept = screened_graph(transfers, settings, screened)
    if settings.weight.node_scope == "screened":
        nodes = graph.vertex_profile(edges, settings.weight.node_time)
    else:
        nodes = graph.vertex_profile(graph.merge_transfers(transfers), settings.weight.node_time)
    return materialize(weights.final_weight(edges, nodes, period.seconds, settings.weight), "weighted-edges"), kept


def detect_rings(transfers: DataFrame, period: Period, settings: Settings = Settings()) -> RingReport:
    """Merge, screen, weigh, search, rank.  An empty ledger gives empty frames."""
    log = RoundLog()
    edges, kept = weighted_graph(transfers, period, settings)
    labels = materialize(detect_communities(edges, settings.louvain, log), "communities")
    of = edges.select(F.explode(F.array("src", "dst")).alias("v"), "mcs").distinct().join(labels, "v").groupBy("comm").agg(F.min("mcs").alias("mcs"))
    scored = risk.community_risk(transfers, edges, labels, period.seconds, settings.risk).join(of, "comm")
    ranked = materialize(risk.risk_levels(risk.risk_curve(scored), settings.risk.cuts), "ranked")
    suspicious = risk.suspicious_components(ranked, settings.risk.min_count)
    return RingReport(edges, kept, labels, ranked, suspicious, log)
