"""User-defined forms of a few expressions, for sessions that call them from SQL; values equal the built-in forms."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def budget(score: float, degree: int, mean: float, delta: float) -> float | None:
    if not degree or degree < 0 or score is None or score <= 0:
        return None
    if mean <= 1:
        return 1.0 if score >= delta * degree else 0.0
    return math.log(mean * score / (delta * degree)) / math.log(mean)


def weight(degree: pd.Series) -> pd.Series:
    return (1.0 / degree.where(degree > 0)).astype(float)


def mass(value: pd.Series) -> float:
    return float(value.sum())


# The functions are made where they are used: workers import this module and have no session.


def budget_udf(*columns):  # noqa: ANN002, ANN201
    """influence_budget, row by row."""
    return F.udf(budget, "double")(*columns)


def weight_udf(column):  # noqa: ANN001, ANN201
    """Reciprocal of the out-degree, by batches; null where there is none."""
    return F.pandas_udf(weight, "double")(column)


def mass_udaf(column):  # noqa: ANN001, ANN201
    """Sum of the values of a group."""
    return F.pandas_udf(mass, "double")(column)


class Walk:
    """Table function: every hop number from 1 to the whole part of a budget."""

    def eval(self, ident: int, hops: float) -> Iterator[tuple[int, int]]:
        for h in range(1, int(hops or 0) + 1):
            yield ident, h


def register(spark: SparkSession) -> None:
    """Names for SQL: hot_budget, hot_weight, hot_walk."""
    spark.udf.register("hot_budget", F.udf(budget, "double"))
    spark.udf.register("hot_weight", F.pandas_udf(weight, "double"))
    spark.udtf.register("hot_walk", F.udtf(Walk, returnType="id bigint, hop int"))


def ranked_kernel(frame: DataFrame) -> DataFrame:
    """score rounded to 6 digits through mapInPandas; the shape of a kernel that works on batches."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(score=b["score"].round(6))

    return frame.mapInPandas(run, frame.schema)
