"""Vertex programs: what a message is, how messages combine and what a vertex makes of them, as column expressions."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hotgraph.operators.components import components
from hotgraph.operators.iterate import CUT_EVERY, deal
from hotgraph.operators.stats import out_degrees
from hotgraph.sources.graphs import ends
from hotgraph.storage import pin, settle


@dataclass(frozen=True)
class VertexProgram:
    """init: first value of a vertex (column id). message: what goes along an edge (columns value, out_deg, src, dst).
    combine: aggregate over a vertex's messages (column message). apply: new value (columns value, got; got is null
    without messages). boundary: the summary's rule for what comes from outside: "constant" for programs whose messages add
    up, None where only exact runs are right. after: a step over all values of a round, such as a normalisation.
    outside: of edges, values of the point before and hot vertices, the few rows (value) by which the rest takes part in
    that step.
    """

    init: Callable[[], Column]
    message: Callable[[], Column]
    combine: Callable[[Column], Column]
    apply: Callable[[], Column]
    boundary: str | None = None
    after: Callable[[DataFrame], DataFrame] | None = None
    outside: Callable[[DataFrame, DataFrame, DataFrame], DataFrame] | None = None


def run(program: VertexProgram, edges: DataFrame, iterations: int | None, style: str = "vertex", vertices: DataFrame | None = None) -> DataFrame:
    """(id, value) after the rounds, or with None once no value changes. Both styles, vertex-centric and gather-sum-apply, lower to this one plan."""
    if style not in ("vertex", "gather"):
        raise ValueError("style is vertex or gather")
    known = (ends(edges) if vertices is None else vertices).join(out_degrees(edges), "id", "left")
    known = known.select("id", F.coalesce("out_deg", F.lit(0)).alias("out_deg"))
    values = pin(known.select("id", "out_deg", program.init().alias("value")), "id")
    met_with, known_values = deal(settle(edges.select("src", "dst"), "links")), None
    for k in count() if iterations is None else range(iterations):
        sent = met_with(values.where("value is not null")).select("dst", program.message().alias("message"))
        got = sent.where("message is not null").groupBy(F.col("dst").alias("id")).agg(program.combine(F.col("message")).alias("got"))
        values = values.join(got, "id", "left").select("id", "out_deg", program.apply().alias("value"))
        if program.after is not None:
            values = program.after(values)
        if iterations is None:
            old, values = known_values, pin(values, "id")
            known_values = values.select(F.col("id").alias("_id"), F.col("value").alias("_value"))
            if old is not None and values.join(old, F.col("id") == F.col("_id")).where("not value <=> _value").isEmpty():
                break
        elif (k + 1) % CUT_EVERY == 0 and k + 1 < iterations:
            values = values.checkpoint(eager=True)
    return values.select("id", "value")


def run_summary(program: VertexProgram, edges: DataFrame, hot: DataFrame, previous: DataFrame, iterations: int) -> DataFrame:
    """(id, value, is_hot) of the vertices of previous(id, value) and hot(id): the program over the hot vertices and the
    edges among them. What comes along edges from others is made once, of their previous values, and held; these
    vertices keep their values. All hot is the exact run from the previous values on; none hot gives these back.
    """
    if program.boundary != "constant":
        raise ValueError("the program has no rule for what comes from outside")
    ids = settle(hot.select("id").distinct(), "hot")
    degree = out_degrees(edges)
    known = previous.select("id", "value").join(ids, "id", "full_outer").join(degree, "id", "left")
    known = settle(known.select("id", F.coalesce("out_deg", F.lit(0)).alias("out_deg"), F.coalesce("value", program.init()).alias("value")), "known")
    aimed = edges.select("src", "dst").join(ids.select(F.col("id").alias("dst")), "dst", "left_semi")
    inner = settle(aimed.join(ids.select(F.col("id").alias("src")), "src", "left_semi"), "inner")
    cold = known.join(ids, "id", "left_anti")
    sent = aimed.join(cold, F.col("src") == F.col("id")).select("dst", program.message().alias("message")).where("message is not null")
    inflow = pin(sent.groupBy("dst").agg(program.combine(F.col("message")).alias("message")).select("dst", "message"), "dst")
    values, met_with = pin(known.join(ids, "id", "left_semi"), "id"), deal(inner)
    rest = None if program.outside is None else settle(program.outside(edges, known.select("id", "value"), ids), "rest")
    for k in range(iterations):
        sent = met_with(values.where("value is not null")).select("dst", program.message().alias("message")).where("message is not null")
        got = sent.unionByName(inflow).groupBy(F.col("dst").alias("id")).agg(program.combine(F.col("message")).alias("got"))
        values = values.join(got, "id", "left").select("id", "out_deg", program.apply().alias("value"))
        if program.after is not None:
            extra = F.lit(None).cast("bigint")
            every = values if rest is None else values.unionByName(rest.select(extra.alias("id"), extra.alias("out_deg"), "value"))
            values = program.after(every).where("id is not null")
        if (k + 1) % CUT_EVERY == 0 and k + 1 < iterations:
            values = values.checkpoint(eager=True)
    return cold.select("id", "value", F.lit(False).alias("is_hot")).unionByName(values.select("id", "value", F.lit(True).alias("is_hot")))


def page_rank(beta: float = 0.85) -> VertexProgram:
    return VertexProgram(
        init=lambda: F.lit(1.0), message=lambda: F.try_divide("value", "out_deg"), combine=F.sum,
        apply=lambda: F.lit(1 - beta) + beta * F.coalesce("got", F.lit(0.0)), boundary="constant",
    )


def eigen_centrality() -> VertexProgram:
    """Sum over in-neighbours, divided by the largest value in each round.

    In a summary the rest takes part in that division by one row: what its largest vertex gets from its in-neighbours.
    """

    def outside(edges: DataFrame, values: DataFrame, hot: DataFrame) -> DataFrame:
        top = values.join(hot, "id", "left_anti").where("value is not null").orderBy(F.col("value").desc(), "id").limit(1)
        near = edges.join(top.select(F.col("id").alias("dst")), "dst", "left_semi")
        return near.join(values, F.col("src") == F.col("id")).agg(F.sum("value").alias("value")).where("value is not null")

    def scaled(values: DataFrame) -> DataFrame:
        most = values.agg(F.max("value").alias("most"))
        share = F.when(F.col("most") > 0, F.col("value") / F.col("most")).otherwise(0.0)
        return values.crossJoin(F.broadcast(most)).select("id", "out_deg", share.alias("value"))

    return VertexProgram(
        init=lambda: F.lit(1.0), message=lambda: F.col("value"), combine=F.sum, apply=lambda: F.coalesce("got", F.lit(0.0)),
        boundary="constant", after=scaled, outside=outside,
    )


def shortest_hops(source: int) -> VertexProgram:
    """Fewest hops from one vertex; null where there is no path."""
    return VertexProgram(
        init=lambda: F.when(F.col("id") == source, F.lit(0)), message=lambda: F.col("value") + 1, combine=F.min,
        apply=lambda: F.least("value", "got"),
    )


def component_labels() -> VertexProgram:
    """Smallest label that reaches a vertex; over symmetric edges, the components."""
    return VertexProgram(
        init=lambda: F.col("id"), message=lambda: F.col("value"), combine=F.min, apply=lambda: F.least("value", "got")
    )


def label_communities(edges: DataFrame, iterations: int) -> DataFrame:
    """(id, value): in each round a vertex takes the most frequent label of its in-neighbours, the smallest on ties.

    Its combine step is a mode over counts: labels are counted in tasks before the shuffle, so hubs stay small.
    """
    values = pin(ends(edges).select("id", F.col("id").alias("value")), "id")
    met_with = deal(settle(edges.select("src", "dst"), "links"))
    for k in range(iterations):
        votes = met_with(values).groupBy("dst", "value").agg(F.count("*").alias("n"))
        won = votes.groupBy(F.col("dst").alias("id")).agg(F.max_by("value", F.struct("n", -F.col("value"))).alias("got"))
        values = values.join(won, "id", "left").select("id", F.coalesce("got", "value").alias("value"))
        if (k + 1) % CUT_EVERY == 0 and k + 1 < iterations:
            values = values.checkpoint(eager=True)
    return values


def connected(edges: DataFrame) -> DataFrame:
    """(id, component): smallest id of each weakly connected component, in rounds that grow with the logarithm of its diameter."""
    named = components(edges.select(F.col("src").alias("a"), F.col("dst").alias("b")))
    alone = edges.where("src = dst").select(F.col("src").alias("id")).distinct().join(named.select(F.col("node").alias("id")), "id", "left_anti")
    return named.select(F.col("node").alias("id"), F.col("root").alias("component")).unionByName(alone.select("id", F.col("id").alias("component")))
