"""Parameters of the methods; the defaults are the published ones where there are any."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from datetime import datetime


@dataclass(frozen=True)
class Period:
    """The half-open time range [start, end) that a graph is built from."""

    start: str
    end: str

    @property
    def seconds(self) -> float:
        return (datetime.fromisoformat(self.end) - datetime.fromisoformat(self.start)).total_seconds()


@dataclass(frozen=True)
class Shares:
    """Weights of standardised variables; they must sum to 1."""

    of: dict[str, float]

    def __post_init__(self):
        if abs(sum(self.of.values()) - 1) > 1e-9:
            raise ValueError(f"shares must sum to 1: {self.of}")

    @classmethod
    def equal(cls, *names: str) -> Shares:
        return cls({n: 1 / len(names) for n in names})


@dataclass(frozen=True)
class ScreenParams:
    """Bounds of a component (strict) and its hubs: degree above, number above."""

    v_lo: int = 10
    v_hi: int = 2000
    hub_degree: int = 20
    n_hubs: int = 7


SMALL_DATA = ScreenParams(10, 2000, 3, 0)


@dataclass(frozen=True)
class WeightParams:
    edge_shares: Shares = field(default_factory=lambda: Shares.equal("money", "times"))
    node_shares: Shares = field(default_factory=lambda: Shares.equal("money", "times", "deg"))
    scope: str = "merged"  # edges are standardised over the merged graph, or over the 'screened' one
    node_scope: str = "screened"
    tau_cap: float | None = 10.0
    node_time: str = "transfer"
    z_cap: float | None = None


@dataclass(frozen=True)
class LouvainParams:
    objective: str = "flow"
    weight: str = "w_e"
    gain: str = "exact"
    resolution: float = 1.0
    strategy: str = "auto"
    local_edges: int = 200_000
    repair: str = "round"
    swap_rule: str = "smaller"  # of two moves that cross, the one to the smaller label stands; 'undo': both go back
    lag_hops: str = "closure"
    delta_mode: str = "carried"
    max_rounds: int = 20
    max_levels: int = 20
    damping: bool = False

    def but(self, **changes) -> LouvainParams:
        return replace(self, **changes)


@dataclass(frozen=True)
class RiskParams:
    shares: Shares = field(default_factory=lambda: Shares.equal("v", "e", "m", "d", "h"))
    segments: int | list[float] = 7
    entropy_sign: int = 1
    degree_scope: str = "inside"
    cuts: tuple[float, float, float] = (0.95, 0.90, 0.80)
    min_count: int = 2
