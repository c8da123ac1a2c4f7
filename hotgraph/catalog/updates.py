"""Streams made from a graph, and updates applied to it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hotgraph.catalog.base import ctes, ends_sql, key
from hotgraph.catalog.core import AT, CHUNK, CHUNKS, GONE, STREAM, key_sql, point
from hotgraph.catalog.graphs import graph
from hotgraph.operators import measures, updates
from hotgraph.operators.stats import degree_change
from hotgraph.sources.graphs import ends


def _del_sql(q: int) -> tuple[str, str]:
    taken = " union all ".join(f"select src, dst from del{k}" for k in range(1, q)) or "select src, dst from e0 where false"
    return (f"del{q}", f"select src, dst from (select src, dst from e0 union all select src, dst from adds where batch < {q}) where (src, dst) not in (select (src, dst) from ({taken})) order by {key_sql(42000 + q)}, src, dst limit {GONE}")


FULL = [*STREAM[:3], *(_del_sql(q) for q in range(1, CHUNKS + 1))]
LOG_SQL = "select batch::int as batch, 'e+' as op, src, dst from adds union all " + " union all ".join(f"select {q}::int, 'e-', src, dst from del{q}" for q in range(1, CHUNKS + 1))


@key("stream_sample", ctes(*STREAM[:2]) + " select src, dst, seq::bigint as seq, batch::int as batch from adds")
def stream_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return updates.sample_additions(graph(spark, sf_dir, "social_urgent"), CHUNK * CHUNKS, CHUNKS)


@key("stream_sample_incidence", ctes(*STREAM[:2]) + f" select src, dst, r::bigint as seq, least((r - 1) // {CHUNK} + 1, {CHUNKS})::int as batch from (select src, dst, row_number() over (order by src, dst) as r from adds)")
def stream_sample_incidence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same edges in the order of their sources: the un-shuffled control."""
    return updates.sample_additions(graph(spark, sf_dir, "social_urgent"), CHUNK * CHUNKS, CHUNKS, order="incidence")


@key("stream_deletions", ctes(*FULL) + " select src, dst, batch from (" + LOG_SQL + ") where op = 'e-'")
def stream_deletions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return point(spark, sf_dir).updates.where("op = 'e-'").select("src", "dst", "batch")


@key("stream_chunks", ctes(*FULL) + " select batch, op, count(*)::bigint as n from (" + LOG_SQL + ") group by batch, op")
def stream_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream through files of one folder a chunk."""
    from hotgraph.sources.tables import scratch

    path = scratch(spark, "stream")
    updates.save_stream(point(spark, sf_dir).updates, path)
    return updates.load_stream(spark, path).groupBy("batch", "op").agg(F.count("*").alias("n"))


@key("apply_adds", ctes(*AT) + " select src, dst from e0 union select src, dst from adds where batch = 1")
def apply_adds(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return updates.merge_updates(at.before, at.updates.where("batch = 1 and op = 'e+'"), at.updates.limit(0))


@key("apply_removes", ctes(*AT) + " select src, dst from e0 except select src, dst from del1")
def apply_removes(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return updates.merge_updates(at.before, at.updates.limit(0), at.updates.where("batch = 1 and op = 'e-'"))


@key("apply_mixed", ctes(*AT) + " select src, dst from e1")
def apply_mixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return updates.merge_updates(at.before, *updates.net_changes(at.updates.where("batch = 1")))


#: A log in which every edge of four chunks is first added, and one in three is removed later, out of order.
_MESSY = "select src, dst, seq as t, 'e+' as op from adds union all select src, dst, seq + 1000, 'e-' from adds where (src + dst) % 3 = 0 union all select src, dst, seq + 2000, 'e+' from adds where (src + dst) % 6 = 0"


@key("apply_last_wins", ctes(*STREAM[:3], ("m", _MESSY), ("f", "select src, dst, max_by(op, t) as op from m group by src, dst")) + " select src, dst from e0 where (src, dst) not in (select (src, dst) from f where op = 'e-') union select src, dst from f where op = 'e+'")
def apply_last_wins(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    a = at.updates.where("op = 'e+'").select("src", "dst", "seq", "op")
    again = lambda m, by, op: a.where((F.col("src") + F.col("dst")) % m == 0).select("src", "dst", (F.col("seq") + by).alias("seq"), F.lit(op).alias("op"))
    log = again(6, 2000, "e+").union(again(3, 1000, "e-")).union(a).withColumn("ts", F.timestamp_seconds("seq"))
    return updates.merge_updates(at.before, *updates.net_changes(log, "last_wins"))


@key("vertex_removal", ctes(*STREAM[:3]) + " select src, dst from e0 where src % 7 <> 0 and dst % 7 <> 0")
def vertex_removal(spark: SparkSession, sf_dir: str) -> DataFrame:
    before = point(spark, sf_dir).before
    return updates.drop_vertices(before, ends(before).where("id % 7 = 0"))


@key("vertex_messages", ctes(*STREAM[:3], ("v", ends_sql("e0"))) + " select id from v where id % 7 <> 0 union select -1")
def vertex_messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices after messages that remove some and add one: those that lose all edges stay."""
    before = point(spark, sf_dir).before
    gone = ends(before).where("id % 7 = 0").select(F.lit("v-").alias("op"), F.col("id").alias("src"))
    log = gone.union(spark.createDataFrame([("v+", -1)], "op string, src bigint")).select("op", "src", F.lit(None).cast("bigint").alias("dst"))
    log = log.withColumn("seq", F.lit(0).cast("bigint")).withColumn("ts", F.lit(None).cast("timestamp"))
    return updates.apply_log(before, ends(before), log)[1]


@key("update_stats", ctes(*FULL, ("v", ends_sql("e0")), ("l", LOG_SQL), ("t", "select distinct batch, id from (select batch, src as id from l union all select batch, dst from l)")) +
    " select l.batch, l.adds::bigint as adds, l.removes::bigint as removes, t.new_vertices::bigint as new_vertices, t.touched::bigint as touched from (select batch, count(*) filter (where op = 'e+') as adds, count(*) filter (where op = 'e-') as removes from l group by batch) l join (select batch, count(*) as touched, count(*) filter (where id not in (select id from v)) as new_vertices from t group by batch) t on t.batch = l.batch")
def update_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return measures.update_stats(at.updates, ends(at.before))


@key("degree_delta", ctes(*AT) + " select d1.id, d0.n::bigint as deg_prev, d1.n::bigint as deg_now from d1 left join d0 on d0.id = d1.id")
def degree_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return degree_change(at.before, at.now)


@key("degree_rolled", ctes(*AT) + " select d1.id, d0.n::bigint as deg_prev, d1.n::bigint as deg_now from d1 left join d0 on d0.id = d1.id")
def degree_rolled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same from the earlier degrees and the chunk alone."""
    from hotgraph.operators.stats import degrees, roll_degrees

    at = point(spark, sf_dir)
    added, removed = updates.net_changes(at.updates.where("batch = 1"))
    return roll_degrees(degrees(at.before), added, removed)


@key("pending_running", ctes(*FULL, ("l", LOG_SQL)) + " select batch, sum(count(*)) over (order by batch)::bigint as pending from l group by batch")
def pending_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Updates pending after each chunk when none is applied."""
    by = Window.partitionBy(F.lit(0)).orderBy("batch")  # one row a chunk
    counts = point(spark, sf_dir).updates.groupBy("batch").agg(F.count("*").alias("n"))
    return counts.select("batch", F.sum("n").over(by).alias("pending"))
