"""The ranking loop. Exact and approximate ranking share it, so that their update rule cannot differ."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.operators.stats import out_degrees
from hotgraph.sources.graphs import ends
from hotgraph.storage import counted, pin, prepare, settle

#: Links, and vertices, up to which all rounds run in one task; about 24 bytes each there. Counted before it is used.
LOCAL_LINKS = 5_000_000
#: Out-links of one vertex up to which they are kept in one partition.
HUB_LINKS = 1_000_000
#: Rounds between lineage cuts of the distributed loop.
CUT_EVERY = 5


def weighted(edges: DataFrame, weight: str | None = None) -> DataFrame:
    """(src, dst, weight): each edge carries its share of what its source sends.

    Without a weight column all out-edges share evenly; with one, in proportion to it.
    """
    if weight is None:
        degree = out_degrees(edges).withColumnRenamed("id", "src")
        return edges.select("src", "dst").join(degree, "src").select("src", "dst", (1 / F.col("out_deg")).alias("weight"))
    total = edges.groupBy("src").agg(F.sum(weight).alias("total"))
    return edges.join(total, "src").select("src", "dst", (F.col(weight) / F.col("total")).alias("weight"))


def power_loop(
    links: DataFrame, vertices: DataFrame, *, beta: float = 0.85, iterations: int = 30, start: DataFrame | None = None,
    inflow: DataFrame | None = None, restart: DataFrame | None = None, tol: float | None = None, norm: str = "l1",
    dangling: str = "none", init: float = 1.0, kernel: str = "distributed", local_links: int | None = None, hub_links: int | None = None,
) -> DataFrame:
    """(id, score) after rounds of: score = (1 - beta) * restart + beta * (what links bring + inflow).

    links (src, dst, weight) are the shares; start (id, score) the first values, `init` where it has none; inflow
    (dst, inflow) what comes from outside in every round; restart (id, share) replaces the even restart of 1. dangling:
    none lets what sinks hold go nowhere, redistribute spreads it evenly. tol ends the rounds once the change by `norm`
    (l1, linf) is at most that. kernel: distributed, local (one task), auto (local if links and vertices are at most
    `local_links` each, both counted).
    """
    if not 0 <= beta <= 1 or iterations < 0 or dangling not in ("none", "redistribute") or norm not in ("l1", "linf"):
        raise ValueError("beta lies in 0..1, iterations is 0 or more, dangling none or redistribute, norm l1 or linf")
    base = vertices.select("id")
    fixed = F.lit(1 - beta)
    if restart is not None:
        base = base.join(restart.select("id", "share"), "id", "left")
        fixed = fixed * F.coalesce("share", F.lit(0.0))
    if inflow is not None:
        base = base.join(inflow.select(F.col("dst").alias("id"), "inflow"), "id", "left")
        fixed = fixed + beta * F.coalesce("inflow", F.lit(0.0))
    first = F.lit(float(init))
    if start is not None:
        base = base.join(start.select("id", F.col("score").alias("held")), "id", "left")
        first = F.coalesce("held", first)
    base = base.select("id", fixed.alias("fixed"), first.cast("double").alias("score"))
    if kernel != "local":
        links = settle(links.select("src", "dst", "weight"), "links")
    if kernel == "auto":
        kernel = "local" if fits(LOCAL_LINKS if local_links is None else local_links, links, vertices) else "distributed"
    if kernel == "local":
        return _local(links, base, beta, iterations, tol, norm, dangling)
    return _distributed(links, base, beta, iterations, tol, norm, dangling, hub_links)


def fits(rows: int, *frames: DataFrame) -> bool:
    """Whether each frame has at most so many rows."""
    return all((counted(df) if hasattr(df, "_settled") else df.limit(rows + 1).count()) <= rows for df in frames)


def deal(links: DataFrame, hub_links: int | None = None) -> Callable[[DataFrame], DataFrame]:
    """Function that gives links(src, dst, ..), which are written, the columns of values(id, ..) at their source.

    Links are pinned by source, so that values pinned by id meet them without a shuffle. Those of a source with over
    hub_links of them would be one partition, so they are pinned by target instead, and the few values of such sources
    (at most the number of links over hub_links) are sent to all tasks.
    """
    limit = HUB_LINKS if hub_links is None else hub_links
    hubs = None
    if not fits(limit, links):
        hubs = settle(links.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") > limit).select("src"), "hubs")
    if hubs is None or hubs.isEmpty():
        whole = pin(links, "src")
        return lambda values: whole.join(values, F.col("src") == F.col("id"))
    usual, heavy = pin(links.join(hubs, "src", "left_anti"), "src"), pin(links.join(hubs, "src", "left_semi"), "dst")

    def met(values: DataFrame) -> DataFrame:
        few = values.join(hubs, F.col("id") == F.col("src"), "left_semi")
        return usual.join(values, F.col("src") == F.col("id")).unionByName(heavy.join(F.broadcast(few), F.col("src") == F.col("id")))

    return met


def _distributed(
    links: DataFrame, base: DataFrame, beta: float, iterations: int, tol: float | None, norm: str, dangling: str, hub_links: int | None
) -> DataFrame:
    met_with, base = deal(links, hub_links), pin(base, "id")
    fixed, scores = base.select("id", "fixed"), base.select("id", "score")
    if dangling == "redistribute":
        sinks = pin(fixed.select("id").join(links.select(F.col("src").alias("id")), "id", "left_anti"), "id")
        n = fixed.count()
    for k in range(iterations):
        sent = met_with(scores).groupBy("dst").agg(F.sum(F.col("score") * F.col("weight")).alias("got"))
        value = F.col("fixed") + beta * F.coalesce("got", F.lit(0.0))
        met = fixed.join(sent.withColumnRenamed("dst", "id"), "id", "left")
        if dangling == "redistribute":
            spread = scores.join(sinks, "id", "left_semi").agg((F.coalesce(F.sum("score"), F.lit(0.0)) / max(n, 1)).alias("spread"))
            met, value = met.crossJoin(F.broadcast(spread)), value + beta * F.col("spread")  # one row
        new = met.select("id", value.alias("score"))
        if tol is not None or (k + 1) % CUT_EVERY == 0 and k + 1 < iterations:
            new = new.checkpoint(eager=True)
        if tol is not None:
            gap = F.abs(F.col("score") - F.col("old"))
            moved = new.join(scores.withColumnRenamed("score", "old"), "id").agg(F.sum(gap) if norm == "l1" else F.max(gap)).first()[0]
            if (moved or 0.0) <= tol:
                return new
        scores = new
    return scores


_ROWS = pa.schema([("kind", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("x", pa.float64()), ("y", pa.float64())])


def _local(
    links: DataFrame, base: DataFrame, beta: float, iterations: int, tol: float | None, norm: str, dangling: str
) -> DataFrame:
    """All rounds in one task, for links whose number has been checked: no shuffle at all after the rows have met."""
    prepare(links.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        t = pa.Table.from_arrays([pa.concat_arrays([b.column(k) for b in held]) for k in range(len(_ROWS))], schema=_ROWS)
        kind, a, b, x, y = (t[c].to_numpy() for c in ("kind", "a", "b", "x", "y"))
        v = kind == 1
        order = np.argsort(a[v])
        ids, fixed, score = a[v][order], x[v][order], y[v][order]
        if not len(ids):
            return
        e = ~v
        src, dst = np.searchsorted(ids, a[e]), np.searchsorted(ids, b[e])
        weight, sinks = x[e], np.ones(len(ids), bool)
        sinks[src] = False
        for _ in range(iterations):
            new = fixed + beta * np.bincount(dst, score[src] * weight, len(ids))
            if dangling == "redistribute":
                new += beta * score[sinks].sum() / len(ids)
            moved = np.abs(new - score)
            score = new
            if tol is not None and (moved.sum() if norm == "l1" else moved.max()) <= tol:
                break
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(score)], ["id", "score"])

    both = links.select(
        F.lit(0).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("weight").alias("x"), F.lit(0.0).alias("y")
    ).union(base.select(F.lit(1), "id", F.lit(0).cast("bigint"), "fixed", "score"))
    return both.coalesce(1).mapInArrow(run, "id bigint, score double")


def rank_exact(
    edges: DataFrame, beta: float = 0.85, iterations: int = 30, *, vertices: DataFrame | None = None, warm: DataFrame | None = None,
    tol: float | None = None, norm: str = "l1", dangling: str = "none", normalize: bool = False, init: float = 1.0,
    weight_col: str | None = None, kernel: str = "distributed", local_links: int | None = None,
) -> DataFrame:
    """(id, score): every vertex sends its score over its out-degree along each edge. Scores average about 1."""
    v = ends(edges) if vertices is None else vertices
    scores = power_loop(
        weighted(edges, weight_col), v, beta=beta, iterations=iterations, start=warm, tol=tol, norm=norm, dangling=dangling,
        init=init, kernel=kernel, local_links=local_links,
    )
    if not normalize:
        return scores
    n = v.agg(F.count("*").alias("n"))
    return scores.crossJoin(F.broadcast(n)).select("id", (F.col("score") / F.col("n")).alias("score"))


def rank_personalised(edges: DataFrame, restart: DataFrame, beta: float = 0.85, iterations: int = 30, **more) -> DataFrame:  # noqa: ANN003
    """Random walk with restart at the ids of restart(id, share); all other vertices restart with 0."""
    return power_loop(weighted(edges), ends(edges), beta=beta, iterations=iterations, restart=restart, **more)


def merge_scores(vertices: DataFrame, hot_scores: DataFrame, previous: DataFrame, default: float) -> DataFrame:
    """(id, score, is_hot) of every vertex: its new score where it is hot, else its previous one."""
    hot = hot_scores.select("id", F.col("score").alias("new"))
    old = previous.select("id", F.col("score").alias("old"))
    return vertices.select("id").join(hot, "id", "left").join(old, "id", "left").select(
        "id", F.coalesce("new", "old", F.lit(default)).alias("score"), F.col("new").isNotNull().alias("is_hot")
    )
