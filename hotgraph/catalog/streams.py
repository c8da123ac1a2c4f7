"""Structured Streaming queries: each drains what the events table holds and returns the final content."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import GRAPH_SQL, ctes, ends_sql, key
from hotgraph.plans.session import Hooks, QuerySession
from hotgraph.schema import Params
from hotgraph.sources.graphs import edge_set
from hotgraph.sources.tables import scratch, table, zoneless
from hotgraph.storage import settle
from hotgraph.streaming import serve, windows

_TOTAL = "round(sum(value::decimal(18,6)), 4)::double"


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return windows.read_events(spark, f"{sf_dir}/events.parque[t]")  # a pattern, as a single file is no source folder


def _split(spark: SparkSession, sf_dir: str, days: int, extra: DataFrame | None = None) -> str:
    """events as files in time order, `days` days to a folder, read in order of their names; extra rows go to the last."""
    path = scratch(spark, "events")
    e = table(spark, sf_dir, "events").withColumn("part", F.floor((F.dayofmonth("ts") - 1) / days))
    for k in range(-(-31 // days)):
        e.where(F.col("part") == k).drop("part").coalesce(1).write.mode("append").parquet(path)
    if extra is not None:
        extra.select(*table(spark, sf_dir, "events").columns).coalesce(1).write.mode("append").parquet(path)
    return path


def _plain(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: zoneless(F.col(n)) for n in names})


@key("st_tumbling", f"select date_trunc('day', ts)::timestamp as window_start, (date_trunc('day', ts) + interval 1 day)::timestamp as window_end, event_type, count(*)::bigint as n, {_TOTAL} as total from events group by 1, 2, 3")
def st_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Complete mode through the memory sink: a row a day and kind."""
    return _plain(windows.in_memory(windows.tumbling(_events(spark, sf_dir)), "complete"), "window_start", "window_end")


@key("st_sliding", f"select s as window_start, s + interval 1 day as window_end, event_type, count(*)::bigint as n, {_TOTAL} as total from (select *, unnest([time_bucket(interval 6 hours, ts, timestamp '1970-01-01') - k * interval 6 hours for k in [0, 1, 2, 3]]) as s from events) group by 1, 2, 3")
def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Update mode: the newest state of each window wins."""
    out = windows.upserted(windows.sliding(_events(spark, sf_dir)), ["window_start", "window_end", "event_type"], "n")
    return _plain(out, "window_start", "window_end")


@key("st_session", """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minute then 0 else 1 end as new from events),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as n from g)
select min(ts) as window_start, max(ts) + interval 30 minute as window_end, user_id, count(*)::bigint as n from s group by user_id, s.n""")
def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Complete mode through a written table: there are nearly as many sessions as events."""
    return _plain(windows.replaced(windows.sessions(_events(spark, sf_dir))), "window_start", "window_end")


@key("st_watermark_late", "select event_type, count(*)::bigint as n from events where ts >= (select max(ts) from events) - interval 1 day or ts < (select max(ts) from events) - interval 1 day group by 1")
def st_watermark_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A last file repeats rows of the first days: they are behind the watermark and change no count."""
    again = table(spark, sf_dir, "events").where("dayofmonth(ts) <= 2")
    path = _split(spark, sf_dir, 6, again)
    daily = windows.upserted(windows.tumbling(windows.read_events(spark, path, 1), late="1 day"), ["window_start", "window_end", "event_type"], "n")
    return daily.groupBy("event_type").agg(F.sum("n").cast("bigint").alias("n"))


@key("st_late_side_table", "select event_id from events where dayofmonth(ts) <= 2")
def st_late_side_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A last file brings the first two days again: the rows that a watermark of a day leaves out."""
    path = _split(spark, sf_dir, 10, table(spark, sf_dir, "events").where("dayofmonth(ts) <= 2"))
    return windows.late_rows(windows.read_events(spark, path, 1)).select("event_id")


@key("st_dedup_watermark", "select event_id, user_id from events")
def st_dedup_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A last file repeats events of the last day; each comes out once."""
    again = table(spark, sf_dir, "events").where("ts > (timestamp_ntz '2024-01-29 12:00:00')")
    path = _split(spark, sf_dir, 10, again)
    return windows.drain(windows.deduplicated(windows.read_events(spark, path, 1))).select("event_id", "user_id")


@key("st_stream_static_join", "select c_mktsegment, count(*)::bigint as n from events join customer on user_id = c_custkey group by 1")
def st_stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    met = _events(spark, sf_dir).join(c, F.col("user_id") == F.col("c_custkey"))
    return windows.in_memory(met.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


@key("st_stream_stream_join", "select c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts > c.ts and p.ts <= c.ts + interval 1 hour")
def st_stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return windows.drain(windows.click_to_purchase(_events(spark, sf_dir), _events(spark, sf_dir)))


@key("st_degree_state", "select user_id, count(*)::bigint as n_events, max(ts) as last_ts from events group by user_id")
def st_degree_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """State of each user over files of ten days."""
    path = _split(spark, sf_dir, 10)
    out = windows.upserted(windows.user_state(windows.read_events(spark, path, 1)), ["user_id"], "n_events")
    return out.select("user_id", "n_events", zoneless(F.timestamp_micros("last_us")).alias("last_ts"))


@key("stream_memory_sink", "select event_type, count(*)::bigint as n from events group by 1")
def stream_memory_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    return windows.in_memory(_events(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n")), "complete")


@key("stream_file_sink", "select event_id, user_id, value from events where event_type = 'purchase'")
def stream_file_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    return windows.drain(_events(spark, sf_dir).where("event_type = 'purchase'").select("event_id", "user_id", "value"))


@key("foreach_batch_sink", GRAPH_SQL["user_next"])
def foreach_batch_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges between successive users, from one batch of the stream, written under the batch's id."""
    from hotgraph.sources.graphs import _successive

    path = scratch(spark, "edges")

    def each(batch: DataFrame, batch_id: int) -> None:
        _successive(batch.withColumn("ts", zoneless(F.col("ts")))).write.mode("overwrite").parquet(f"{path}/version={batch_id}")

    _events(spark, sf_dir).writeStream.foreachBatch(each).option("checkpointLocation", f"{path}-state").trigger(
        availableNow=True
    ).start().awaitTermination()
    return edge_set(spark.read.parquet(path))


def _loop_sql() -> str:
    """Edges after each of the four files, and the vertices whose out-degree moved by over 2 % since the file before."""
    parts = []
    for b in range(1, 5):
        e = GRAPH_SQL["user_next"].replace("from events ", f"from events where dayofmonth(ts) <= {10 * b}")
        parts += [(f"E{b}", e), (f"N{b}", f"select v.id, count(e.src) as n from ({ends_sql(f'E{b}')}) v left join E{b} e on e.src = v.id group by v.id")]
    rows = " union all ".join(
        f" select {b}::int as batch, 'approximate' as strategy, (select count(*) from E{b})::bigint as n_edges, "
        f"(select count(*) from N{b} a left join N{max(1, b - 1)} o on o.id = a.id where o.id is null or abs(a.n - o.n) > 0.02::double * o.n)::bigint as n_hot"
        for b in range(1, 5)
    )
    return ctes(*parts) + rows


@key("st_query_loop", _loop_sql())
def st_query_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Serving from the live stream: the first ten days are the graph, each later file ends with a query."""
    path = _split(spark, sf_dir, 10)
    first = serve.events_as_updates(table(spark, sf_dir, "events").where("dayofmonth(ts) <= 10")).select("src", "dst")
    session = QuerySession(settle(first, "first"), Params(0.02, 0, None, iterations=5), Hooks(), name="user_next").start()
    out, chain = scratch(spark, "answers"), serve.EventChain(scratch(spark, "chain"))

    def each(batch: DataFrame, batch_id: int) -> None:
        serve.process_batch(session, chain.updates(batch, batch_id))
        session.scores.write.mode("overwrite").parquet(f"{out}/version={batch_id}")

    windows.read_events(spark, path, 1).writeStream.foreachBatch(each).option("checkpointLocation", f"{out}-state").trigger(
        availableNow=True
    ).start().awaitTermination()
    return session.run_log().select(F.col("query").alias("batch"), "strategy", "n_edges", "n_hot")
