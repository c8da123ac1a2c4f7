"""The summary graph: hot vertices, the edges among them, and one constant contribution for all others."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.operators.iterate import merge_scores, power_loop
from hotgraph.operators.stats import out_degrees


@dataclass(frozen=True)
class Summary:
    """hot (id), inner (src, dst, weight), inflow (dst, inflow, n_edges)."""

    hot: DataFrame
    inner: DataFrame
    inflow: DataFrame


def incoming(edges: DataFrame, hot: DataFrame, scores: DataFrame, degrees: DataFrame | None = None) -> DataFrame:
    """(src, dst, out_deg, score, inner): edges that end in the hot set. Degrees count all edges, also those left out.

    One pass over the edges; edges that end outside are dropped by a semi join before anything else meets them.
    """
    degrees = out_degrees(edges) if degrees is None else degrees
    ids = hot.select("id").distinct()
    aimed = edges.select("src", "dst").join(ids.select(F.col("id").alias("dst")), "dst", "left_semi")
    flagged = aimed.join(ids.select(F.col("id").alias("src"), F.lit(True).alias("inner")), "src", "left")
    return (
        flagged.join(degrees.select(F.col("id").alias("src"), "out_deg"), "src")
        .join(scores.select(F.col("id").alias("src"), "score"), "src", "left")
        .select("src", "dst", "out_deg", "score", F.coalesce("inner", F.lit(False)).alias("inner"))
    )


def build_summary(edges: DataFrame, hot: DataFrame, scores: DataFrame, degrees: DataFrame | None = None) -> Summary:
    """scores are the stored ones of the point before; degrees (id, out_deg) those of the current graph."""
    return split(incoming(edges, hot, scores, degrees), hot)


def split(aimed: DataFrame, hot: DataFrame) -> Summary:
    """The summary from incoming()'s rows; write these first where both parts will be read."""
    inner = aimed.where("inner").select("src", "dst", (1 / F.col("out_deg")).alias("weight"))
    cold = aimed.where("not inner").groupBy("dst").agg(
        F.sum(F.coalesce("score", F.lit(0.0)) / F.col("out_deg")).alias("inflow"), F.count("*").alias("n_edges")
    )
    return Summary(hot.select("id").distinct(), inner, cold)


def outside_total(summary: Summary) -> DataFrame:
    """One row: the whole contribution of the vertices outside, and the number of edges that bring it."""
    return summary.inflow.agg(
        F.coalesce(F.sum("inflow"), F.lit(0.0)).alias("outside_total"), F.coalesce(F.sum("n_edges"), F.lit(0)).alias("boundary_edges")
    )


def summary_ratio(summary: Summary, edges: DataFrame) -> DataFrame:
    """One row: inner_edges, boundary_edges (before they are put together by target), all_edges, ratio."""
    inner = summary.inner.agg(F.count("*").alias("inner_edges"))
    cold = outside_total(summary).select("boundary_edges")
    every = edges.agg(F.count("*").alias("all_edges"))
    ratio = F.try_divide(F.col("inner_edges") + F.col("boundary_edges"), "all_edges")
    return inner.crossJoin(cold).crossJoin(every).withColumn("ratio", ratio)


def rank_approximate(
    summary: Summary, previous: DataFrame, vertices: DataFrame, *, beta: float = 0.85, iterations: int = 30, warm: bool = True,
    kernel: str = "distributed", local_links: int | None = None,
) -> DataFrame:
    """(id, score, is_hot): the loop over the summary, what comes from outside held constant; all others keep their score.

    warm starts the hot vertices from their previous scores, else from the common first value. An empty hot set gives
    the previous scores; one of all vertices gives the exact loop.
    """
    hot = power_loop(
        summary.inner, summary.hot, beta=beta, iterations=iterations, inflow=summary.inflow, start=previous if warm else None, kernel=kernel,
        local_links=local_links,
    )
    return merge_scores(vertices, hot, previous, 1 - beta)
