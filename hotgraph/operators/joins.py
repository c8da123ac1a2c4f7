"""Joins that Spark has no operator for, as compositions of equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Share of the left rows above which a key is salted.
HOT_SHARE = 0.01


def range_join(left: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of left with the ranges low <= value < high: both sides meet by bins of `width`, then the bounds decide.

    A range is copied once for each bin it covers, so width should be near the usual length of a range.
    """
    binned = left.withColumn("_bin", F.floor(F.col(value) / width))
    spread = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return binned.join(spread, "_bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin")


def interval_join(left: DataFrame, right: DataFrame, key: str, start: str, at: str, seconds: int) -> DataFrame:
    """Pairs of the same key with start < at <= start + seconds, by bins of that length: each left row goes to two."""
    us = seconds * 1_000_000
    number = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / us)
    a = left.withColumn("_bin", F.explode(F.array(number(start), number(start) + 1)))
    b = right.withColumn("_bin", number(at))
    near = (F.col(at) > F.col(start)) & (F.col(at) <= F.col(start) + F.expr(f"interval {seconds} seconds"))
    return a.join(b, [key, "_bin"]).where(near).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, strict: bool = True) -> DataFrame:
    """left with the columns of the last right row of its key before it (or at it, if not strict); null where none.

    One union and one window a key, so one shuffle and no pairs.
    """
    mine = [c for c in left.columns if c not in (key, ts)]
    theirs = [c for c in right.columns if c not in (key, ts)]
    a = left.select(key, ts, F.struct(*mine).alias("_l"), F.lit(None).cast(right.select(F.struct(*theirs)).schema[0].dataType).alias("_r"))
    b = right.select(key, ts, F.lit(None).cast(left.select(F.struct(*mine)).schema[0].dataType).alias("_l"), F.struct(*theirs).alias("_r"))
    side = F.col("_l").isNull().cast("int")
    order = [F.col(ts), side.asc() if strict else side.desc()]
    w = Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    both = a.union(b).withColumn("_last", F.last("_r", ignorenulls=True).over(w))
    return both.where("_l is not null").select(key, ts, "_l.*", "_last.*")


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int, share: float = HOT_SHARE) -> DataFrame:
    """Inner join whose hot left keys are dealt over `salts` partitions; only their right rows are copied, to each salt.

    Hot is a key with over `share` of the left rows, counted first, so there are fewer than 1 / share of them. Neither side
    is broadcast: what is copied is not in the planner's sizes.
    """
    least = left.count() * share
    hot = [r[0] for r in left.where(F.col(key).isNotNull()).groupBy(key).count().where(F.col("count") > least).collect()]
    zero = F.lit(0).cast("bigint")
    every = F.sequence(zero, F.lit(salts - 1).cast("bigint"))
    a = left.withColumn("_salt", F.when(F.col(key).isin(hot), F.pmod(F.xxhash64(*left.columns), F.lit(salts))).otherwise(zero))
    b = right.withColumn("_salt", F.explode(F.when(F.col(key).isin(hot), every).otherwise(F.array(zero))))
    return a.join(b.hint("merge"), [key, "_salt"]).drop("_salt")
