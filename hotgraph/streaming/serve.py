"""Serving from a stream of update messages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.plans.session import QuerySession
from hotgraph.schema import UPDATES, require
from hotgraph.sources.graphs import with_next
from hotgraph.storage import settle


def process_batch(session: QuerySession, messages: DataFrame, query_at_end: bool = True) -> list[int]:
    """Messages of one micro-batch in the order of seq: updates before a query enter it, later ones wait for the next.

    Returns the numbers of the queries answered. Only the sequence numbers of queries are collected.
    """
    held = settle(require(messages, UPDATES), "batch")
    asked = sorted(r.seq for r in held.where("op = 'query'").select("seq").collect())
    answered, low = [], None
    for at in asked:
        part = held.where(F.col("seq") < at) if low is None else held.where((F.col("seq") > low) & (F.col("seq") < at))
        session.enqueue(part)
        session.query()
        answered.append(session.n_query)
        low = at
    session.enqueue(held if low is None else held.where(F.col("seq") > low))
    if query_at_end:
        session.query()
        answered.append(session.n_query)
    return answered


def serve(source: DataFrame, session: QuerySession, path: str, checkpoint: str, query_at_end: bool = True):  # noqa: ANN201
    """Start answering a streaming frame of messages. Each batch's answer is written to version=<batch id>: a batch that
    is run again after a failure overwrites its own folder, so answers appear once.
    """

    def each(batch: DataFrame, batch_id: int) -> None:
        process_batch(session, batch, query_at_end)
        session.scores.write.mode("overwrite").parquet(f"{path}/version={batch_id}")

    return source.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def events_as_updates(events: DataFrame, last: DataFrame | None = None) -> DataFrame:
    """Edge additions between successive users of some events, in the shape of the update log.

    last: one row (event_id, ts, user_id), the event before these.
    """
    own = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id").where("user_id is not null")
    every = own if last is None else own.unionByName(last.select("event_id", "ts", "user_id"))
    pairs = with_next(every, "user_id", ["ts", "event_id"]).select(
        F.col("event_id").alias("seq"), "ts", F.lit(0).alias("batch"), F.lit("e+").alias("op"), F.col("user_id").alias("src"), F.col("next").alias("dst")
    )
    return pairs.where("dst is not null and src <> dst")


class EventChain:
    """Updates of one micro-batch of events after the other, the edge between the batches included.

    The last event so far is written under the batch's id, so a batch that is run again after a failure starts from the
    event before it, not from its own.
    """

    def __init__(self, path: str) -> None:
        self.path = path

    def updates(self, events: DataFrame, batch_id: int) -> DataFrame:
        spark, last = events.sparkSession, None
        if batch_id:
            last = spark.read.parquet(f"{self.path}/last={batch_id - 1}")
        own = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id").where("user_id is not null")
        every = own if last is None else own.unionByName(last)
        every.orderBy(F.col("ts").desc(), F.col("event_id").desc()).limit(1).write.mode("overwrite").parquet(f"{self.path}/last={batch_id}")
        return events_as_updates(events, last)
