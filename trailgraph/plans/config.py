"""Configuration of a run; every decision on a silent point of SURVEY section 0 is a field."""

from __future__ import annotations

from dataclasses import dataclass, replace
from datetime import timedelta

from trailgraph.operators.risk import SEGMENTS


@dataclass(frozen=True)
class TrailConfig:
    ledger: str = "events"
    delta_w: timedelta = timedelta(days=1)
    min_weight: float = 0.5
    combine: str = "max"
    count_mode: str = "edges"
    top_fraction: float = 1e-6
    hubs: int | None = 0
    degree_kind: str = "txn"
    window: str | None = None
    assign: str = "both"
    weight: str | None = "w"
    resolution: float = 1.0
    quality: str = "modularity"
    max_comm_size: int | None = 200
    seed: int = 42
    engine: str = "auto"
    task_limit: int = 200_000
    segments: tuple[str, ...] = SEGMENTS
    quantifier: str = "all"
    sunk_lo: float = 50.0
    sunk_hi: float = 150.0
    flow_threshold: int = 500_000
    hold: str = "window"
    skip_prune: bool = False

    def but(self, **kw) -> TrailConfig:
        return replace(self, **kw)


E6h = TrailConfig(delta_w=timedelta(hours=6))
E1d = TrailConfig()
E3d = TrailConfig(delta_w=timedelta(days=3), min_weight=0.3)
R3d = TrailConfig(ledger="trade", delta_w=timedelta(days=3), flow_threshold=500_000_000)
R7d = TrailConfig(ledger="trade", delta_w=timedelta(days=7), flow_threshold=500_000_000)
R1d = R7d.but(delta_w=timedelta(days=1))
