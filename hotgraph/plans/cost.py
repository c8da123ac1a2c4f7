"""Row counts a strategy will read, to choose one before iterating."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Cost:
    """Relative cost of a row in the loop, in a broadcast scan, and in the final merge."""

    loop: float = 1.0
    scan: float = 0.2
    merge: float = 0.3

    def exact(self, edges: int, iterations: int) -> float:
        return iterations * edges * self.loop

    def approximate(self, edges: int, vertices: int, inner: int, boundary: int, iterations: int, hops: int) -> float:
        return (1 + hops) * edges * self.scan + boundary + iterations * inner * self.loop + vertices * self.merge


def pays(edges: int, vertices: int, inner: int, boundary: int, iterations: int, hops: int, most_share: float = 0.7, cost: Cost = Cost()) -> bool:
    """Whether the summary is worth iterating: a small enough share of the edges, and cheaper than the exact loop."""
    if edges and (inner + boundary) / edges > most_share:
        return False
    return cost.approximate(edges, vertices, inner, boundary, iterations, hops) < cost.exact(edges, iterations)
