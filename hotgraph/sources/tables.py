"""Reading the given tables, and round trips through other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.storage import prepare, shared_root


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, name: str) -> str:
    import uuid

    return f"{shared_root(spark)}/hotgraph/{uuid.uuid4().hex}-{name}"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events with ts as an instant (UTC), as watermarks need it."""
    return table(spark, sf_dir, "events").withColumn("ts", utc("ts"))


def utc(name: str):  # noqa: ANN201
    """A zoneless timestamp column as the instant it names in UTC, whatever the session's zone."""
    return F.convert_timezone(F.lit("UTC"), F.current_timezone(), F.col(name)).cast("timestamp")


def zoneless(c):  # noqa: ANN001, ANN201
    """An instant as the zoneless timestamp of UTC, whatever the session's zone."""
    return F.convert_timezone(F.current_timezone(), F.lit("UTC"), c.cast("timestamp_ntz"))


def round_trip(df: DataFrame, kind: str, name: str) -> DataFrame:
    """df written in a format and read again with its own schema, not an inferred one."""
    path = scratch(df.sparkSession, name)
    writer = df.write.option("header", True) if kind == "csv" else df.write
    writer.format(kind).save(path)
    reader = df.sparkSession.read.schema(df.schema)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def edge_list(spark: SparkSession, path: str) -> DataFrame:
    """Edges of a text file with two whole numbers and a tab on each line; lines that do not fit are left out."""
    parts = F.split("value", "\t")
    read = spark.read.text(path).select(
        F.when(F.size(parts) == 2, F.expr("try_cast(split(value, '\\t')[0] as bigint)")).alias("src"),
        F.when(F.size(parts) == 2, F.expr("try_cast(split(value, '\\t')[1] as bigint)")).alias("dst"),
    )
    return read.where("src is not null and dst is not null")


def malformed(spark: SparkSession, path: str) -> DataFrame:
    """One row: lines, good, bad."""
    return spark.read.text(path).agg(
        F.count("*").alias("lines"), F.count_if(F.col("value").rlike(r"^-?\d+\t-?\d+$")).alias("good"),
    ).withColumn("bad", F.col("lines") - F.col("good"))


def bucketed(edges: DataFrame, name: str, key: str = "src", buckets: int = 8) -> DataFrame:
    """edges as a table bucketed and sorted by key: joins on the key with another such table need no exchange."""
    spark = edges.sparkSession
    spark.sql(f"drop table if exists {name}")
    edges.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
    return spark.table(name)
