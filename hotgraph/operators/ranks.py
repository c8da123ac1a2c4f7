"""Positions of all rows of a frame without one window over everything."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hotgraph.functions.expressions import rank_order
from hotgraph.storage import settle


#: Ranks that one window may number.
FEW = 100_000


def numbered(df: DataFrame, *order: Column, name: str = "rank", partitions: int | None = None) -> DataFrame:
    """df with numbers 1..n in the given order: range partitions, their sizes, and offsets of one row each."""
    parts = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = settle(df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()), "ranges")
    before = Window.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row a partition
    offsets = dealt.groupBy("_part").agg(F.count("*").alias("n")).select("_part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_base"))
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return dealt.join(F.broadcast(offsets), "_part").withColumn(name, F.col("_base") + inside).drop("_part", "_base")


def global_rank(scores: DataFrame, score: str = "score", ident: str = "id", partitions: int | None = None) -> DataFrame:
    """scores with rank 1..n by (score descending, id)."""
    return numbered(scores, *rank_order(score, ident), partitions=partitions)


def top(scores: DataFrame, k: int) -> DataFrame:
    """(rank, id, score) of the k highest: heaps in each task and one merge, for many ranks by global_rank()."""
    if k > FEW:
        ranked = global_rank(scores.select("id", "score")).where(F.col("rank") <= k)
        return ranked.select(F.col("rank").cast("bigint").alias("rank"), "id", "score")
    few = scores.select("id", "score").orderBy(*rank_order()).limit(k)
    ranked = few.withColumn("rank", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*rank_order())))  # k rows
    return ranked.select(F.col("rank").cast("bigint").alias("rank"), "id", "score")


def list_length(vertices: int, share: float = 0.1, least: int = 10) -> int:
    """Length of a compared ranking: a share of the vertices, not under `least`, not over all of them."""
    return min(vertices, max(least, -(-round(vertices * share * 1e9) // 10**9)))
