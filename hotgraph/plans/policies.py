"""Which strategy answers a query: functions from the pending changes and the query's number to a strategy's name."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

REUSE, APPROXIMATE, RECOMPUTE = "reuse", "approximate", "recompute"


@dataclass(frozen=True)
class Pending:
    """What has changed since the last computed answer. query counts from 1."""

    query: int
    adds: int = 0
    removes: int = 0
    touched: int = 0
    n_vertices: int = 0
    n_edges: int = 0
    tier: str = "balanced"

    @property
    def share(self) -> float:
        return (self.adds + self.removes) / max(1, self.n_edges)


Policy = Callable[[Pending], str]


def always(strategy: str) -> Policy:
    if strategy not in (REUSE, APPROXIMATE, RECOMPUTE):
        raise ValueError(strategy)
    return lambda _: strategy


def periodic(m: int, between: str = APPROXIMATE) -> Policy:
    """Exact at every m-th query, so that errors of approximate answers do not pile up."""
    return lambda p: RECOMPUTE if p.query % m == 0 else between


def by_change(low: float, high: float) -> Policy:
    """Reuse below a share `low` of changed edges, recompute from `high` on, approximate between."""
    return lambda p: REUSE if p.share < low else RECOMPUTE if p.share >= high else APPROXIMATE


def by_tier(tiers: dict[str, Policy] | None = None) -> Policy:
    """By what the query asks for: latency, balanced or accuracy."""
    known = tiers or {"latency": by_change(0.001, 1.0), "balanced": by_change(0.0, 0.2), "accuracy": periodic(5)}
    return lambda p: known[p.tier](p)
