"""The hot set: seeds by degree change, a ring of hops around them, and a ring by estimated influence."""

from __future__ import annotations

import math
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.functions.expressions import changed, influence_budget, within_budget
from hotgraph.operators.localhot import covers, select_hot_local
from hotgraph.operators.stats import degree_change, degrees, mean_degree, out_degrees
from hotgraph.schema import Params
from hotgraph.sources.graphs import ends
from hotgraph.storage import settle

#: Score of a vertex that has none yet: the common first value of the ranking.
FIRST = 1.0


def select_changed(change: DataFrame, r: float, zero_policy: str = "include") -> DataFrame:
    """(id, reason) of the seeds among change(id, deg_prev, deg_now): new vertices, and those that moved by over r.

    From degree 0 to more the ratio has no value; zero_policy says whether that includes a vertex.
    """
    moved = changed("deg_prev", "deg_now", r)
    if zero_policy == "exclude":
        moved = moved & ((F.col("deg_prev") > 0) | F.lit(r < 0))
    return change.where(F.col("deg_prev").isNull() | moved).select(
        "id", F.when(F.col("deg_prev").isNull(), "new").otherwise("changed").alias("reason")
    )


def _directed(edges: DataFrame, direction: str) -> DataFrame:
    """(src, dst) so that a hop goes from src to dst."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return {"out": edges.select("src", "dst"), "in": back, "both": edges.select("src", "dst").union(back)}[direction]


def expand_hops(edges: DataFrame, seeds: DataFrame, n: int, direction: str = "out") -> DataFrame:
    """(id, hop) of the vertices 1..n hops from any seed, without the seeds.

    Each round joins the last ring only, drops what has been visited, and ends early once a ring is empty. Rings are
    written, so the planner knows their sizes and broadcasts them when they are small; what has been visited is one
    frame of them all.
    """
    ring = visited = settle(seeds.select("id", F.lit(0).alias("hop")).distinct(), "seeds")
    hops = _directed(edges, direction)
    for h in range(1, n + 1):
        reached = hops.join(ring.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()
        ring = settle(reached.join(visited.select("id"), "id", "left_anti").select("id", F.lit(h).alias("hop")), f"ring{h}")
        if ring.isEmpty():
            break
        visited = visited.union(ring)
    return visited.where("hop > 0")


def expand_by_influence(
    edges: DataFrame, anchors: DataFrame, inside: DataFrame, scores: DataFrame, delta: float, *, mean: float, mode: str = "candidate",
    threshold: str = "absolute", direction: str = "out", max_hops: int | None = None, facts: DataFrame | None = None,
) -> DataFrame:
    """(id, hop, budget) of vertices outside `inside` that the anchors' changes may still move by delta.

    candidate: a vertex's own budget covers its distance from the nearest anchor. anchor: the budget of the anchor it is
    reached from does, and the largest remaining budget is carried along. path_product: budget is the largest
    contribution that arrives, divided by the actual degree at every hop, and it is at least delta. With a relative
    threshold scores count as 1. mean is the mean degree; at most 1 allows one hop only. Without max_hops the ring ends
    where budgets or contributions do. facts: (id, out_deg) of the vertices that have edges, where known already.
    """
    if delta <= 0:
        raise ValueError("delta is above 0")
    score = F.lit(1.0) if threshold == "relative" else F.coalesce("score", F.lit(FIRST))
    facts = ends(edges).join(out_degrees(edges), "id", "left") if facts is None else facts.select("id", "out_deg")
    known = facts.join(scores.select("id", "score"), "id", "left").select("id", F.coalesce("out_deg", F.lit(0)).alias("deg"), score.alias("s"))
    known = settle(known, "known")
    hops, start = _directed(edges, direction), anchors.select("id").distinct()
    if mode == "path_product":
        found = _products(hops, start, known, delta, max_hops)
    elif mode == "anchor":
        found = _carried(hops, start, known, delta, mean, max_hops)
    else:
        limit = known.agg(F.max(influence_budget("s", "deg", mean, delta))).first()[0]
        most = math.floor((limit or 0.0) + 1e-9)
        most = most if max_hops is None else min(max_hops, most)
        reached = expand_hops(edges, start, max(most, 0), direction)
        found = reached.join(known, "id").where(within_budget("hop", "s", "deg", mean, delta)).select(
            "id", "hop", influence_budget("s", "deg", mean, delta).alias("budget")
        )
    return found.join(inside.select("id"), "id", "left_anti")


def _carried(hops: DataFrame, start: DataFrame, known: DataFrame, delta: float, mean: float, max_hops: int | None) -> DataFrame:
    left = influence_budget("s", "deg", mean, delta)
    front = start.join(known, "id").select("id", left.alias("budget")).where("budget >= 1")
    return _spread(hops, front, lambda f: f.withColumn("out", F.col("budget") - 1), F.lit(0.0), F.lit(1.0), max_hops)


def _products(hops: DataFrame, start: DataFrame, known: DataFrame, delta: float, max_hops: int | None) -> DataFrame:
    front = start.join(known.where("deg > 0"), "id").select("id", F.col("s").alias("budget"))
    degree = known.where("deg > 0").select("id", "deg")
    sends = lambda f: f.join(degree, "id").withColumn("out", F.col("budget") / F.col("deg"))
    return _spread(hops, front, sends, F.lit(delta), F.lit(0.0), max_hops)


def _spread(hops, front, sends, least, again, max_hops) -> DataFrame:  # noqa: ANN001
    """(id, hop, budget): the largest value that arrives, over at most max_hops if given, and the hop it first arrives at."""
    best = None
    front = settle(front, "front")
    for h in count(1) if max_hops is None else range(1, max_hops + 1):
        out = sends(front).select(F.col("id").alias("src"), "out")
        got = hops.join(out, "src").groupBy(F.col("dst").alias("id")).agg(F.max("out").alias("budget")).where(F.col("budget") >= least)
        if best is None:
            front = settle(got.select("id", F.lit(h).alias("hop"), "budget"), "reached")
            best = front
        else:
            old = best.select("id", F.col("hop").alias("h0"), F.col("budget").alias("b0"))
            front = settle(
                got.join(old, "id", "left").where("b0 is null or budget > b0")
                .select("id", F.coalesce("h0", F.lit(h)).alias("hop"), "budget"), "reached",
            )
            best = settle(
                best.unionByName(front).groupBy("id").agg(F.min("hop").alias("hop"), F.max("budget").alias("budget")), "best"
            )
        front = front.where(F.col("budget") >= again)
        if front.isEmpty():
            break
    return best


def select_hot(
    now: DataFrame, before: DataFrame, scores: DataFrame, params: Params, *, previous_scores: DataFrame | None = None,
    touched: DataFrame | None = None, change: DataFrame | None = None, kernel: str = "distributed", facts: DataFrame | None = None,
) -> DataFrame:
    """(id, reason, hop) of the hot set at a measurement point, each vertex once with the first reason that holds.

    now, before: edges at this point and the one before; change: degrees at both where they are known already.
    previous_scores: scores one point earlier, for the score_change signal. touched: vertices that updates touched, for
    the mean degree over these. kernel: local does it in one task where localhot has the readings; the caller has counted
    the edges then. facts: (id, out_deg, in_deg) of all vertices, where known already.
    """
    p = params
    change = degree_change(before, now, p.degree) if change is None else change
    if kernel == "local" and covers(p):
        return select_hot_local(now, change, signal(scores, previous_scores, p), p)
    seeds = settle(select_changed(change, p.r, p.zero_policy), "seeds")
    ring = expand_hops(now, seeds, p.n, p.direction)
    core = seeds.select("id", "reason", F.lit(0).alias("hop")).union(ring.select("id", F.lit("ring"), "hop"))
    if p.delta is None:
        return core
    anchors = ring if p.anchor == "ring" else core
    used = None if facts is None else facts.where(F.col("out_deg") + F.col("in_deg") > 0)
    return core.union(
        expand_by_influence(
            now, anchors, core, signal(scores, previous_scores, p), p.delta, mean=mean_of(now, touched, p, used), mode=p.mode,
            threshold=p.threshold, direction=p.direction, max_hops=p.max_hops, facts=used,
        ).select("id", F.lit("influence"), "hop")
    )


def signal(scores: DataFrame, previous: DataFrame | None, p: Params) -> DataFrame:
    """(id, score) that the influence ring weighs: the score, or its relative change since the point before."""
    if p.signal == "score" or previous is None:
        return scores.select("id", "score")
    old = previous.select("id", F.col("score").alias("old"))
    return scores.join(old, "id").select("id", F.abs(F.try_divide(F.col("score") - F.col("old"), F.col("old"))).alias("score"))


def mean_of(edges: DataFrame, touched: DataFrame | None, p: Params, used: DataFrame | None = None) -> float:
    """Edges a vertex, of the vertices that have edges or of those touched; used: (id, out_deg) of the former if known."""
    if p.mean_degree == "touched" and touched is not None:
        near = degrees(edges).join(touched.select("id").distinct(), "id", "left_semi")
        return near.agg(F.avg("degree")).first()[0] or 0.0
    if used is not None:
        return used.agg(F.try_divide(F.sum("out_deg"), F.count("*"))).first()[0] or 0.0
    return mean_degree(edges).first()["mean_degree"] or 0.0
