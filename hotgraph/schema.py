"""Frames of the engine and the parameters of an approximate query."""

from __future__ import annotations

from dataclasses import dataclass, fields, replace

from pyspark.sql import DataFrame

EDGES = "src bigint, dst bigint"
VERTICES = "id bigint"
SCORES = "id bigint, score double"
DEGREES = "id bigint, deg_prev bigint, deg_now bigint"
HOT = "id bigint, reason string, hop int"
UPDATES = "seq bigint, ts timestamp, batch int, op string, src bigint, dst bigint"
INNER = "src bigint, dst bigint, weight double"
INFLOW = "dst bigint, inflow double, n_edges bigint"

#: Kinds of update messages.
ADD_EDGE, REMOVE_EDGE, ADD_VERTEX, REMOVE_VERTEX, QUERY = "e+", "e-", "v+", "v-", "query"


def require(df: DataFrame, schema: str) -> DataFrame:
    """df with exactly the named columns, or ValueError where one is missing or of another type."""
    have = dict(df.dtypes)
    for field in schema.split(", "):
        name, kind = field.split(" ")
        if have.get(name) != kind:
            raise ValueError(f"column {name} should be {kind}; the frame has {df.dtypes}")
    return df.select(*(f.split(" ")[0] for f in schema.split(", ")))


@dataclass(frozen=True)
class Params:
    """Thresholds of the hot set and of the ranking.

    r: relative degree change above which a vertex is a seed. n: hops around the seeds. delta: least contribution for
    the influence ring, None for no such ring. The other fields name the readings that the method leaves open.
    """

    r: float = 0.2
    n: int = 1
    delta: float | None = 0.5
    beta: float = 0.85
    iterations: int = 30
    degree: str = "out"  # out, in, total
    direction: str = "out"  # out, in, both
    mode: str = "candidate"  # candidate, anchor, path_product
    threshold: str = "absolute"  # absolute, relative
    signal: str = "score"  # score, score_change
    anchor: str = "seeds+ring"  # ring, seeds+ring
    mean_degree: str = "graph"  # graph, touched
    zero_policy: str = "include"  # include, exclude: vertices whose degree was 0
    max_hops: int | None = None  # None: the influence ring ends by itself
    warm: bool = True
    allow_all: bool = False

    def __post_init__(self) -> None:
        choices = {
            "degree": ("out", "in", "total"), "direction": ("out", "in", "both"),
            "mode": ("candidate", "anchor", "path_product"), "threshold": ("absolute", "relative"),
            "signal": ("score", "score_change"), "anchor": ("ring", "seeds+ring"), "mean_degree": ("graph", "touched"),
            "zero_policy": ("include", "exclude"),
        }
        for name, allowed in choices.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {allowed}")
        if self.r < 0 and not self.allow_all:
            raise ValueError("a negative r makes every vertex hot; pass allow_all=True if that is meant")
        if self.n < 0 or self.n != int(self.n):
            raise ValueError("n is a whole number of hops, 0 or more")
        if self.delta is not None and self.delta <= 0:
            raise ValueError("delta is above 0, or None")
        if not 0 <= self.beta <= 1:
            raise ValueError("beta lies between 0 and 1")
        if self.iterations < 0:
            raise ValueError("iterations is 0 or more")

    def but(self, **changes) -> Params:  # noqa: ANN003
        return replace(self, **changes)

    @property
    def label(self) -> str:
        """r, n and delta, and any reading that is not the usual one."""
        usual, plain = Params(), ("r", "n", "delta", "beta", "iterations")
        other = [str(getattr(self, f.name)) for f in fields(self) if f.name not in plain and getattr(self, f.name) != getattr(usual, f.name)]
        return "_".join([f"r{self.r:g}_n{self.n}_d{self.delta if self.delta is None else format(self.delta, 'g')}", *other])
