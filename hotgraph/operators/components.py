"""Connected components by repeated contraction, on DataFrames only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.storage import discard, settle


def components(links: DataFrame) -> DataFrame:
    """(node, root) for every node of links(a, b); root is the smallest node of its component.

    Each round sends a node to the smallest of itself and its neighbours, and once more to that one's choice,
    then renames the links and drops those inside one name. A path halves at least, so rounds grow with the
    logarithm of the diameter. Minima are combined before the shuffle, so a hub costs one row per task.
    Null ends and loops are ignored; an empty input gives an empty result.
    """
    one = links.select("a", "b").where("a <> b")
    open_ = settle(one.union(one.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    named = open_.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct()
    while not open_.isEmpty():
        to = open_.groupBy("a").agg(F.min("b").alias("p")).select("a", F.least("a", "p").alias("p"))
        up = to.select(F.col("a").alias("p"), F.col("p").alias("q"))
        to, before = settle(to.join(up, "p").select("a", F.col("q").alias("p")), "parents"), (open_, named)
        left = to.select(F.col("a"), F.col("p").alias("pa"))
        right = to.select(F.col("a").alias("b"), F.col("p").alias("pb"))
        open_ = settle(
            open_.join(left, "a").join(right, "b").where("pa <> pb")
            .select(F.col("pa").alias("a"), F.col("pb").alias("b")).distinct(),
            "links",
        )
        moved = to.select(F.col("a").alias("root"), "p")
        named = settle(named.join(moved, "root", "left").select("node", F.coalesce("p", "root").alias("root")), "named")
        discard(to, *before)
    return named
