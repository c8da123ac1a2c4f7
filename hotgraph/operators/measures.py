"""Accuracy, work and statistics. Rankings are frames (rank, id), ranks from 1."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hotgraph.storage import prepare, settle

#: Weight below which deeper ranks cannot change a value.
TINY = 1e-12
#: Depths in a chunk of weights, and groups on a side of the grid that counts inversions.
CHUNK, SIDE = 1 << 20, 2000


def depth_needed(p: float, k: int) -> int:
    """Depth beyond which rank-biased overlap no longer changes by TINY, at most k."""
    return min(k, max(1, math.ceil(math.log(TINY * (1 - p)) / math.log(p)))) if 0 < p < 1 else k


def _sum(term: Callable[[np.ndarray], np.ndarray], first: int, last: int) -> float:
    """Sum of term over first..last, in chunks, until the terms no longer count."""
    total = 0.0
    for at in range(first, last + 1, CHUNK):
        total += (part := float(term(np.arange(at, min(at + CHUNK, last + 1), dtype=float)).sum()))
        if part <= abs(total) * 1e-17:
            break
    return total


def _weights(spark: SparkSession, k: int, term: Callable[[Column], Column]) -> DataFrame:
    """(m, w) for each depth m of 1..k: w is the sum of term over the depths m..k.

    Made where it is used: chunks of depths are added up from behind, and what lies behind a chunk comes from one row
    for each chunk.
    """
    d = spark.range(1, k + 1).select(F.col("id").alias("m"), F.floor((F.col("id") - 1) / CHUNK).alias("chunk"), term(F.col("id")).alias("t"))
    behind = Window.partitionBy(F.lit(0)).orderBy(F.col("chunk").desc()).rowsBetween(Window.unboundedPreceding, -1)  # a row a chunk
    rest = d.groupBy("chunk").agg(F.sum("t").alias("t")).select("chunk", F.coalesce(F.sum("t").over(behind), F.lit(0.0)).alias("rest"))
    inside = F.sum("t").over(Window.partitionBy("chunk").orderBy(F.col("m").desc()))
    return d.join(rest, "chunk").select("m", (inside + F.col("rest")).alias("w"))


def _powers(p: float) -> Callable[[Column], Column]:
    """Term p^(d-1) / d of a depth d."""
    return lambda d: F.pow(F.lit(p), d - 1) / d


def common(a: DataFrame, b: DataFrame) -> DataFrame:
    """(id, i, j, m) of the ids in both lists: their ranks and the depth from which both lists hold them."""
    x, y = a.select("id", F.col("rank").alias("i")), b.select("id", F.col("rank").alias("j"))
    return x.join(y, "id").withColumn("m", F.greatest("i", "j"))


def rbo(a: DataFrame, b: DataFrame, k: int, p: float = 0.98, form: str = "ext") -> DataFrame:
    """One row: k, p, rbo of the first k ranks of two lists. An item's share is the tail sum of weights from its depth,
    so the whole is one join of two short lists and a sum.

    base: depths to k only. min: the least that longer lists could give; res: how much more they could give at most.
    ext: extrapolated, 1 for equal lists. Depths whose weights no longer count are not read (see depth_needed).
    """
    if form not in ("base", "min", "res", "ext"):
        raise ValueError("form is base, min, res or ext")
    k = max(1, k)
    used = k if form in ("min", "res") else depth_needed(p, k)
    met = common(a.where(F.col("rank") <= used), b.where(F.col("rank") <= used))
    sums = met.join(_weights(a.sparkSession, used, _powers(p)), "m").agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("s"), F.count("*").alias("x"))
    head = [F.lit(k).alias("k"), F.lit(p).alias("p")]
    if form in ("base", "ext"):  # beyond the depth needed p^k is nothing
        return sums.select(*head, ((1 - p) * F.col("s") + (F.lit(p**used / used) * F.col("x") if form == "ext" else F.lit(0.0))).alias("rbo"))
    s, x = sums.first()
    power = lambda d: p**d / d
    sigma = _sum(power, 1, k)
    if form == "min":
        value = (1 - p) / p * (p * s - x * sigma - x * math.log1p(-p))
    else:
        tail = _sum(power, k + 1, 2 * k - x)
        value = 2 * p**k - p ** (2 * k - x) - (1 - p) / p * (2 * k * tail + x * (-math.log1p(-p) - sigma - tail))
    return a.sparkSession.createDataFrame([(k, p, value)], "k int, p double, rbo double")


def rbo_uneven(short: DataFrame, long: DataFrame, s: int, l: int, p: float = 0.98) -> DataFrame:  # noqa: E741
    """One row: k_short, k_long, p, rbo: extrapolated overlap of lists of s and l ranks, s at most l.

    Between the depths s and l the short list is taken to agree as much as it did at s.
    """
    met = common(short.where(F.col("rank") <= s), long.where(F.col("rank") <= l)).where(F.col("m") <= l)
    sums = met.join(_weights(short.sparkSession, l, _powers(p)), "m").agg(
        F.coalesce(F.sum("w"), F.lit(0.0)).alias("sum"), F.count("*").alias("xl"), F.count_if(F.col("m") <= s).alias("xs")
    )
    tail = _sum(lambda d: p**d * (d - s) / (s * d), s + 1, l) / p
    value = (1 - p) * (F.col("sum") + F.col("xs") * tail) + p**l * ((F.col("xl") - F.col("xs")) / l + F.col("xs") / s)
    return sums.select(F.lit(s).alias("k_short"), F.lit(l).alias("k_long"), F.lit(p).alias("p"), value.alias("rbo"))


def avg_overlap(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """One row: mean over depths 1..k of the share of items both lists hold at that depth."""
    met = common(a.where(F.col("rank") <= k), b.where(F.col("rank") <= k)).join(_weights(a.sparkSession, k, lambda d: 1 / d), "m")
    return met.agg((F.coalesce(F.sum("w"), F.lit(0.0)) / k).alias("avg_overlap")).select(F.lit(k).alias("k"), "avg_overlap")


def overlap_at(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    met = common(a.where(F.col("rank") <= k), b.where(F.col("rank") <= k))
    return met.agg(F.count("*").alias("n_common")).select(F.lit(k).alias("k"), "n_common", (F.col("n_common") / k).alias("overlap"))


def inversions(x: np.ndarray) -> int:
    """Pairs of places whose values are in descending order; values are distinct."""
    x = np.argsort(np.argsort(x)).astype(np.int64)
    n, width, total = len(x), 1, 0
    while width < n:
        run = np.arange(n) // (2 * width)  # two sorted runs side by side
        right = np.arange(n) % (2 * width) >= width
        left_keys, right_keys = (run * n + x)[~right], (run * n + x)[right]
        lefts = np.minimum(width, n - run[right] * 2 * width)
        smaller = np.searchsorted(left_keys, right_keys) - np.searchsorted(left_keys, run[right] * n)
        total += int((lefts - smaller).sum())
        x = x[np.lexsort((x, run))]
        width *= 2
    return total


def _inside(pairs: DataFrame, by: str) -> DataFrame:
    """(n): pairs in descending order, over both lists, in each group of by; with "y" only between different "x"."""

    def count(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("i")
        n = inversions(group["j"].to_numpy())
        if by == "y":
            n -= sum(inversions(part.to_numpy()) for _, part in group.groupby("x")["j"])
        return pd.DataFrame({"n": [n]})

    return pairs.groupBy(by).applyInPandas(count, "n bigint")


def kendall_tau(a: DataFrame, b: DataFrame, k: int, side: int = SIDE) -> DataFrame:
    """One row: n_items, concordant, discordant, tau over the items in both lists of k.

    Ranks of both lists fall into at most `side` ranges each. Pairs in one range of the first list are counted in its
    group, pairs in one range of the second only in that one's, and all others from the counts of the grid of ranges,
    which is at most side * side numbers.
    """
    prepare(a.sparkSession)
    width = max(1, -(-k // side))
    met = common(a.where(F.col("rank") <= k), b.where(F.col("rank") <= k)).select("i", "j")
    met = settle(met.select("i", "j", F.floor((F.col("i") - 1) / width).alias("x"), F.floor((F.col("j") - 1) / width).alias("y")), "pairs")
    near = _inside(met, "x").unionByName(_inside(met, "y")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("near"))

    def apart(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid = np.zeros((side + 1, side + 1), np.int64)
        for batch in batches:
            x, y, n = (c.to_numpy() for c in batch.columns)
            grid[x, y] += n
        after = np.zeros_like(grid)  # items in earlier ranges of the first list and later ones of the second
        after[1:, :-1] = grid[::, ::-1].cumsum(0).cumsum(1)[:-1, ::-1][:, 1:]
        yield pa.RecordBatch.from_arrays([pa.array([int((grid * after).sum())]), pa.array([int(grid.sum())])], ["far", "n"])

    cells = met.groupBy("x", "y").agg(F.count("*").alias("c")).coalesce(1)  # at most side * side rows
    far = cells.mapInArrow(apart, "far bigint, n bigint").agg(F.coalesce(F.sum("far"), F.lit(0)).alias("far"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    n = F.col("n")
    return near.crossJoin(far).select(
        n.alias("n_items"), (F.shiftright(n * (n - 1), 1) - F.col("near") - F.col("far")).cast("bigint").alias("concordant"), (F.col("near") + F.col("far")).alias("discordant")
    ).withColumn("tau", F.try_divide(F.col("concordant") - F.col("discordant"), F.col("concordant") + F.col("discordant")))


def score_error(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: l1, linf and the mean relative error of scores a against the exact b."""
    met = a.select("id", F.col("score").alias("x")).join(b.select("id", F.col("score").alias("y")), "id", "full_outer")
    gap = F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0)))
    return met.agg(F.sum(gap).alias("l1"), F.max(gap).alias("linf"), F.avg(F.try_divide(gap, F.abs("y"))).alias("mean_relative"))


def rank_shift(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: the largest and the mean number of places between the ranks of an id in both lists."""
    gap = F.abs(F.col("i") - F.col("j"))
    return common(a, b).agg(F.max(gap).alias("max_shift"), F.avg(gap).alias("mean_shift"))


def speedup(exact: DataFrame, approximate: DataFrame, kind: str = "total") -> DataFrame:
    """(query, speedup) from two run logs of the same stream: total time, or its compute phase only."""
    spent = lambda name: (
        F.aggregate(F.map_values("phases"), F.lit(0.0), lambda acc, x: acc + x) if kind == "total" else F.col("phases")["compute"]
    ).alias(name)
    met = exact.select("query", spent("a")).join(approximate.select("query", spent("b")), "query")
    return met.select("query", F.try_divide("a", "b").alias("speedup"))


def work_saved(log: DataFrame, iterations: int) -> DataFrame:
    """(query, vertex_ratio, edge_ratio, processed_share): rows that the loop reads against those of the exact loop."""
    processed = F.col("inner_edges") * iterations + F.col("boundary_edges")
    return log.select(
        "query", F.try_divide(F.col("n_hot") + 1, "n_vertices").alias("vertex_ratio"),
        F.try_divide(F.col("inner_edges") + F.col("boundary_edges"), "n_edges").alias("edge_ratio"),
        F.try_divide(processed, F.col("n_edges") * iterations).alias("processed_share"),
    )


def best_worst(runs: DataFrame, n: int = 3) -> DataFrame:
    """(metric, set_id, mean, side, place) of the n best and n worst parameter sets of each metric by mean over queries."""
    means = runs.groupBy("metric", "set_id").agg(F.avg("value").alias("mean"))
    by = Window.partitionBy("metric")
    placed = means.withColumn("b", F.row_number().over(by.orderBy(F.round("mean", 9).desc(), "set_id"))).withColumn(
        "w", F.row_number().over(by.orderBy(F.round("mean", 9).asc(), "set_id"))
    )
    pick = lambda c, side: placed.where(F.col(c) <= n).select("metric", "set_id", "mean", F.lit(side).alias("side"), F.col(c).alias("place"))
    return pick("b", "best").union(pick("w", "worst"))


def series(runs: DataFrame) -> DataFrame:
    """(set_id, metric, query, value) with a first point of 1 at query 0 for the overlap."""
    own = runs.select("set_id", "metric", "query", "value")
    zero = own.where("metric = 'rbo'").select("set_id", "metric", F.lit(0).alias("query"), F.lit(1.0).alias("value")).distinct()
    return zero.unionByName(own)


def update_stats(log: DataFrame, vertices: DataFrame) -> DataFrame:
    """(batch, adds, removes, new_vertices, touched) of pending updates, against the vertices that are there."""
    ids = log.select("batch", "op", F.explode(F.array("src", "dst")).alias("id")).where("id is not null")
    known = vertices.select("id", F.lit(True).alias("known"))
    per = ids.select("batch", "id").distinct().join(known, "id", "left").groupBy("batch").agg(
        F.count("*").alias("touched"), F.count_if(F.col("known").isNull()).alias("new_vertices")
    )
    counts = log.groupBy("batch").agg(F.count_if(F.col("op") == "e+").alias("adds"), F.count_if(F.col("op") == "e-").alias("removes"))
    return counts.join(per, "batch").select("batch", "adds", "removes", "new_vertices", "touched")
