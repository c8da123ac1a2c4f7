"""Windows, late rows, duplicates, joins and state over a stream of events(event_id, ts, user_id, event_type, value)."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.sources.tables import scratch, utc
from hotgraph.storage import delete, prepare

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_at_once: int | None = None) -> DataFrame:
    """A streaming frame over the Parquet files at path, ts as an instant."""
    prepare(spark)
    reader = spark.readStream.schema(EVENTS)
    if files_at_once:
        reader = reader.option("maxFilesPerTrigger", files_at_once)
    return reader.parquet(path).withColumn("ts", utc("ts"))


def tumbling(events: DataFrame, size: str = "1 day", late: str = "1 day") -> DataFrame:
    return _windowed(events, F.window("ts", size), late)


def sliding(events: DataFrame, size: str = "1 day", step: str = "6 hours", late: str = "1 day") -> DataFrame:
    return _windowed(events, F.window("ts", size, step), late)


def _windowed(events: DataFrame, window, late: str) -> DataFrame:  # noqa: ANN001
    counted = events.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(
        F.count("*").alias("n"), F.round(F.sum(F.col("value").cast("decimal(18,6)")), 4).cast("double").alias("total")
    )
    return counted.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    counted = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "user_id", "n")


def deduplicated(events: DataFrame, late: str = "2 days") -> DataFrame:
    """Each event_id once, remembered as long as the watermark asks."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_to_purchase(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Pairs of one user with the purchase after the click and within the time; both sides' state is bounded by it."""
    a = clicks.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t0"))
    b = purchases.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("t1"))
    on = (F.col("u") == F.col("user_id")) & (F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr(f"interval {within}"))
    return a.withWatermark("t0", late).join(b.withWatermark("t1", late), on).select("click", "purchase")


def user_state(events: DataFrame) -> DataFrame:
    """(user_id, n_events, last_us) after every batch a user appears in; one small state a user."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        n, last = state.get if state.exists else (0, 0)
        for f in frames:
            n, last = n + len(f), max(last, int(f["us"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n_events": [n], "last_us": [last]})

    picked = events.select("user_id", F.unix_micros("ts").alias("us"))
    return picked.groupBy("user_id").applyInPandasWithState(
        step, "user_id bigint, n_events bigint, last_us bigint", "n bigint, last bigint", "update", "NoTimeout"
    )


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All rows of a stream over what its source holds now, as a written table. append only: rows are final."""
    spark = stream.sparkSession
    path = scratch(spark, "stream")
    stream.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", f"{path}-state").trigger(
        availableNow=True
    ).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def in_memory(stream: DataFrame, mode: str) -> DataFrame:
    """The result table of a stream in complete or append mode, through the memory sink; for small results only."""
    spark, name = stream.sparkSession, f"hot_{uuid.uuid4().hex}"
    path = scratch(spark, "memory")
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", path).trigger(
        availableNow=True
    ).start().awaitTermination()
    return spark.table(name)


def replaced(stream: DataFrame) -> DataFrame:
    """The result table of a stream in complete mode, of any size: each batch writes all of it under its id, and the last
    one is read. What it supersedes is deleted when it is written.
    """
    spark = stream.sparkSession
    path = scratch(spark, "complete")
    stood: list[int] = []

    def each(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/version={batch_id}")
        for old in [b for b in stood if b != batch_id]:
            delete(spark, f"{path}/version={old}")
        stood[:] = [batch_id]

    stream.writeStream.outputMode("complete").foreachBatch(each).option("checkpointLocation", f"{path}-state").trigger(
        availableNow=True
    ).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/version={stood[0]}") if stood else spark.createDataFrame([], stream.schema)


def upserted(stream: DataFrame, keys: list[str], order: str) -> DataFrame:
    """The last row of each key of a stream in update mode: batches are written by their id and the newest wins."""
    spark = stream.sparkSession
    path = scratch(spark, "updates")

    def each(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    stream.writeStream.outputMode("update").foreachBatch(each).option("checkpointLocation", f"{path}-state").trigger(
        availableNow=True
    ).start().awaitTermination()
    rows = spark.read.parquet(path)
    values = [c for c in stream.columns if c not in keys]
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*values), F.struct(order, "batch")).alias("_v"))
    return last.select(*keys, "_v.*")


def late_rows(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """The side table of a stream's late rows, after it has been drained: rows older than the watermark, which is `late`
    below the largest ts of all batches before.

    That largest ts is written under each batch's id, as are the late rows, so a batch that runs again overwrites its own.
    """
    spark = stream.sparkSession
    path = scratch(spark, "late")

    def each(batch: DataFrame, batch_id: int) -> None:
        top = batch.agg(F.max("ts").alias("top"))
        if batch_id:
            before = spark.read.parquet(f"{path}/top={batch_id - 1}")
            mark = before.select((F.col("top") - F.expr(f"interval {late}")).alias("_mark"))  # one row
            batch.crossJoin(F.broadcast(mark)).where("ts < _mark").drop("_mark").write.mode("overwrite").parquet(f"{path}/rows/version={batch_id}")
            top = top.union(before).agg(F.max("top").alias("top"))
        else:
            batch.limit(0).write.mode("overwrite").parquet(f"{path}/rows/version=0")
        top.write.mode("overwrite").parquet(f"{path}/top={batch_id}")

    stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")
