"""Other ways to save work, for comparison: sampled edges, dropped tasks, shed updates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hotgraph.functions.expressions import stable_key
from hotgraph.operators.iterate import rank_exact
from hotgraph.sources.graphs import ends


def _share(key: Column) -> Column:
    """The key's first 12 hexadecimal digits as a number from 0 to below 1."""
    return F.conv(F.substring(key, 1, 12), 16, 10).cast("bigint") / F.lit(float(16**12))


def sample_edges(edges: DataFrame, fraction: float, seed: int = 42) -> DataFrame:
    return edges.where(_share(stable_key("src", "dst", seed=seed)) < fraction)


def baseline_sample(edges: DataFrame, fraction: float, seed: int = 42, **rank) -> DataFrame:  # noqa: ANN003
    """Exact ranking of a fixed sample of the edges, over all vertices."""
    return rank_exact(sample_edges(edges, fraction, seed), vertices=ends(edges), **rank)


def baseline_drop_tasks(edges: DataFrame, n_parts: int, keep: int, seed: int = 42, **rank) -> DataFrame:  # noqa: ANN003
    """Exact ranking as if only `keep` of n_parts tasks ran: edges are dealt to parts by the key of their source."""
    part = F.floor(_share(stable_key("src", seed=seed)) * n_parts)
    return rank_exact(edges.where(part < keep), vertices=ends(edges), **rank)


def baseline_shed(updates: DataFrame, keep: float, seed: int = 42) -> DataFrame:
    """Updates with only a fixed share of them kept."""
    return updates.where(_share(stable_key("src", "dst", "op", seed=seed)) < keep)
