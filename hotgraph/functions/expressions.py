"""Column expressions; all stay inside code generation."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

Number = Column | str | float


def _col(x: Number) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(float(x))


def changed(deg_prev: Number, deg_now: Number, r: float) -> Column:
    """Relative degree change above r, without dividing; 0 to something counts as above any r, 0 to 0 as unchanged."""
    a, b = _col(deg_prev), _col(deg_now)
    return (F.abs(b - a) > F.lit(float(r)) * a) | F.lit(r < 0)


def influence_budget(score: Number, degree: Number, mean: Number, delta: float) -> Column:
    """Hops over which a vertex's contribution stays at delta or more, with the mean degree at every hop.

    Outside the formula's domain: 1 or 0 hops where the mean is at most 1, by whether the first contribution
    reaches delta; null for vertices that send nothing.
    """
    s, d, m = _col(score), _col(degree), _col(mean)
    first = F.when(s >= F.lit(delta) * d, 1.0).otherwise(0.0)
    inside = F.log(m * s / (F.lit(delta) * d)) / F.log(m)
    return F.when((d > 0) & (s > 0), F.when(m > 1, inside).otherwise(first))


def within_budget(hop: Number, score: Number, degree: Number, mean: Number, delta: float) -> Column:
    """hop <= influence_budget, without a logarithm: exact where the budget is a whole number."""
    h, s, d, m = _col(hop), _col(score), _col(degree), _col(mean)
    grown = F.when(m > 1, F.pow(m, h - 1)).when(h <= 1, 1.0)
    return F.coalesce((d > 0) & (s > 0) & (s >= F.lit(delta) * d * grown), F.lit(False))


def rank_order(score: str = "score", ident: str = "id") -> list[Column]:
    """Order of a ranking: higher scores first, rounded so that the noise of sums does not permute ties; then ids."""
    return [F.round(F.col(score), 9).desc(), F.col(ident).asc()]


def stable_key(*columns: str, seed: int = 42) -> Column:
    """MD5 of the columns and a seed as text: the same order in any engine."""
    return F.md5(F.concat_ws("-", *(F.col(c).cast("string") for c in columns), F.lit(str(seed))).cast("binary"))
