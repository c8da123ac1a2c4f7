"""A mergeable count-min sketch as a frame: one row a cell, summed before the shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROWS, WIDTH = 5, 2048


def _cells(c: Column, rows: int, width: int) -> Column:
    return F.array(*(F.struct(F.lit(k).alias("row"), F.pmod(F.xxhash64(c, F.lit(k)), F.lit(width)).alias("cell")) for k in range(rows)))


def count_min(df: DataFrame, column: str, rows: int = ROWS, width: int = WIDTH) -> DataFrame:
    """(row, cell, n): at most rows * width rows whatever the input. Overestimates by at most 2 n / width with
    probability 1 - 2^-rows.
    """
    cells = df.select(F.explode(_cells(F.col(column), rows, width)).alias("c")).groupBy("c.row", "c.cell")
    return cells.agg(F.count("*").alias("n"))


def estimate(sketch: DataFrame, asked: DataFrame, column: str, rows: int = ROWS, width: int = WIDTH) -> DataFrame:
    """asked with `estimate`: the least of a key's cells."""
    tried = asked.withColumn("c", F.explode(_cells(F.col(column), rows, width))).withColumns({"row": F.col("c.row"), "cell": F.col("c.cell")})
    met = tried.join(F.broadcast(sketch), ["row", "cell"])
    return met.groupBy(*asked.columns).agg(F.min("n").alias("estimate"))
