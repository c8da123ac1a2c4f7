"""User-defined functions: each gives the value of the built-in form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import ctes, key
from hotgraph.catalog.core import KNOWN, SCORED, SUMMARY, STREAM, _r, point, summary
from hotgraph.functions import udfs
from hotgraph.operators.stats import mean_degree, out_degrees
from hotgraph.storage import prepare

_BUDGET = "case when deg > 0 and s > 0 then ln(m * s / (0.5 * deg)) / ln(m) end"


def _known(spark: SparkSession, sf_dir: str) -> DataFrame:
    prepare(spark)
    at = point(spark, sf_dir)
    from hotgraph.sources.graphs import ends

    mean = mean_degree(at.now).first()["mean_degree"]
    return ends(at.now).join(out_degrees(at.now), "id", "left").join(at.scores, "id", "left").select(
        "id", F.coalesce("out_deg", F.lit(0)).alias("deg"), F.coalesce("score", F.lit(1.0)).alias("s"), F.lit(mean).alias("m")
    )


@key("udf_scalar_budget", ctes(*SCORED, *KNOWN) + f" select id, round({_BUDGET}, 6) as budget from known")
def udf_scalar_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _known(spark, sf_dir).select("id", F.round(udfs.budget_udf("s", "deg", "m", F.lit(0.5)), 6).alias("budget"))


@key("udf_pandas_weight", ctes(*SCORED, *KNOWN) + " select id, round(case when deg > 0 then 1.0::double / deg end, 6) as weight from known")
def udf_pandas_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = udfs.weight_udf(F.col("deg").cast("double"))
    return _known(spark, sf_dir).select("id", w.alias("w")).select("id", F.round(F.when(~F.isnan("w"), F.col("w")), 6).alias("weight"))


@key("udaf_pandas_rank_mass", ctes(*SUMMARY) + " select dst, round(sum(coalesce(score, 0) / deg), 6) as inflow from aimed where not inside group by dst")
def udaf_pandas_rank_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    from hotgraph.catalog.core import hot
    from hotgraph.operators.summary import incoming

    at = point(spark, sf_dir)
    prepare(spark)
    cold = incoming(at.now, hot(spark, sf_dir), at.scores).where("not inner")
    cold = cold.select("dst", (F.coalesce("score", F.lit(0.0)) / F.col("out_deg")).alias("sent"))
    return cold.groupBy("dst").agg(udfs.mass_udaf("sent").alias("inflow")).select("dst", F.round("inflow", 6).alias("inflow"))


@key("udtf_walk_expand", ctes(*SCORED, *KNOWN, ("b", f"select id, {_BUDGET} as budget from known")) + " select id, unnest(range(1, floor(budget)::bigint + 1))::int as hop from b where budget >= 1")
def udtf_walk_expand(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    known = _known(spark, sf_dir)
    return spark.sql(
        "select w.id, w.hop from (select id, hot_budget(s, deg, m, 0.5D) as budget from {known}) b, lateral hot_walk(b.id, b.budget) w", known=known
    )


@key("map_in_pandas_kernel", ctes(*SCORED) + " select id, round(score, 6) as score from x10")
def map_in_pandas_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    prepare(spark)
    return udfs.ranked_kernel(point(spark, sf_dir).scores)


@key("cogroup_kernel", ctes(*STREAM[:3], ("l", "select * from adds")) + " select src, ((select count(*) from e0 where e0.src = l.src) + count(*))::bigint as out_deg from l group by src")
def cogroup_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degrees after the stream's additions, for the sources it touches, by cogrouping old degrees with the additions."""
    import pandas as pd

    prepare(spark)
    at = point(spark, sf_dir)
    old = out_degrees(at.before).select(F.col("id").alias("src"), "out_deg")
    new = at.updates.where("op = 'e+'").select("src", "dst")

    def merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(b):
            return pd.DataFrame({"src": [], "out_deg": []}).astype("int64")
        return pd.DataFrame({"src": [b.src.iloc[0]], "out_deg": [int(a.out_deg.sum()) + len(b)]})

    return old.groupBy("src").cogroup(new.groupBy("src")).applyInPandas(merge, "src bigint, out_deg bigint")


@key("udf_sql_weight", ctes(*SUMMARY) + " select src, dst, round(weight, 6) as weight from inner_")
def udf_sql_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The summary's weights through the registered name, against the built-in division."""
    udfs.register(spark)
    prepare(spark)
    inner = summary(spark, sf_dir).inner.select("src", "dst", F.round(1 / F.col("weight")).alias("deg"))
    return _r(inner.select("src", "dst", F.call_function("hot_weight", F.col("deg")).alias("weight")), "weight")
