"""Accuracy measures of the approximate answer against the exact one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import ctes, key
from hotgraph.catalog.core import APPROX, EXACT_NOW, P, ROUNDS, _r, approximate, exact_now, summary
from hotgraph.operators import measures
from hotgraph.operators.ranks import global_rank, list_length, top
from hotgraph.sources.tables import table
from hotgraph.storage import settle

#: Length of the lists at sf 0.01 and above: a tenth of the vertices, as SQL and as code.
_K = "least((select count(*) from v1), greatest(10, ceil(0.1 * (select count(*) from v1))))"
LISTS = [
    *APPROX, *EXACT_NOW,
    ("kk", f"select {_K}::bigint as k"),
    ("la", "select id, row_number() over (order by round(score, 9) desc, id) as rank from approx"),
    ("lb", f"select id, row_number() over (order by round(score, 9) desc, id) as rank from y{ROUNDS}"),
    ("met", "select a.id, a.rank as i, b.rank as j, greatest(a.rank, b.rank) as m from la a join lb b on a.id = b.id, kk where a.rank <= k and b.rank <= k"),
    ("depth", "select unnest(range(1, (select k + 1 from kk))) as d"),
    ("w", "select d as m, sum(pow(0.98::double, d - 1) / d) over (order by d desc) as w from depth"),
    ("sums", "select coalesce(sum(w), 0) as s, count(*) as x from met join w using (m)"),
]


def lists(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, int]:
    a, b = approximate(spark, sf_dir), exact_now(spark, sf_dir)
    k = list_length(b.count())
    return settle(top(a, k), "top"), settle(top(b, k), "top"), k


def _rbo_key(form: str, value: str) -> None:
    @key(f"rbo_{form}", ctes(*LISTS) + f" select k::int as k, 0.98::double as p, round({value}, 6) as rbo from sums, kk")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        a, b, k = lists(spark, sf_dir)
        return _r(measures.rbo(a, b, k, 0.98, form), "rbo")


_SIGMA = "(select sum(pow(0.98::double, d) / d) from depth)"
_MIN = f"0.02::double / 0.98 * (0.98 * s - x * {_SIGMA} - x * ln(0.02::double))"
_TAIL = "(select coalesce(sum(pow(0.98::double, d) / d), 0) from (select unnest(range((select k + 1 from kk), (select 2 * k - x + 1 from kk, sums))) as d))"
_rbo_key("ext", "0.02::double * s + pow(0.98::double, k) / k * x")
_rbo_key("base", "0.02::double * s")
_rbo_key("min", _MIN)
_rbo_key("res", f"2 * pow(0.98::double, k) - pow(0.98::double, 2 * k - x) - 0.02::double / 0.98 * (2 * k * {_TAIL} + x * (-ln(0.02::double) - {_SIGMA} - {_TAIL}))")


@key("rbo_uneven", ctes(*LISTS, ("ss", "select (k // 2)::bigint as s from kk"), ("mu", "select m from met, ss where i <= s"), ("xd", "select d, (select count(*) from mu where m <= d) as x from depth"),
    ("parts", "select (select sum(x::double / d * pow(0.98::double, d)) from xd) as a, (select sum((select x from xd where d = (select s from ss)) * (d - s)::double / (s * d) * pow(0.98::double, d)) from depth, ss where d > s) as b, (select x from xd where d = (select k from kk)) as xl, (select x from xd where d = (select s from ss)) as xs"))
    + " select s::int as k_short, k::int as k_long, 0.98::double as p, round(0.02::double / 0.98 * (a + b) + ((xl - xs)::double / k + xs::double / s) * pow(0.98::double, k), 6) as rbo from parts, kk, ss")
def rbo_uneven(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b, k = lists(spark, sf_dir)
    return _r(measures.rbo_uneven(a, b, k // 2, k), "rbo")


@key("rbo_full", ctes(*APPROX, *EXACT_NOW, ("la", "select id, row_number() over (order by round(score, 9) desc, id) as rank from approx"), ("lb", f"select id, row_number() over (order by round(score, 9) desc, id) as rank from y{ROUNDS}"),
    ("nn", "select count(*) as n from v1"), ("met", "select greatest(a.rank, b.rank) as m from la a join lb b on a.id = b.id"), ("w", "select d as m, sum(pow(0.98::double, d - 1) / d) over (order by d desc) as w from (select unnest(range(1, (select n + 1 from nn))) as d)"))
    + " select n::int as k, 0.98::double as p, round(0.02::double * (select sum(w) from met join w using (m)) + pow(0.98::double, n), 6) as rbo from nn")
def rbo_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole rankings; positions come from range partitions, not one window."""
    a, b = approximate(spark, sf_dir), exact_now(spark, sf_dir)
    n = b.count()
    return _r(measures.rbo(global_rank(a), global_rank(b), n), "rbo")


@key("avg_overlap", ctes(*LISTS, ("xd", "select d, (select count(*) from met where m <= d) as x from depth")) + " select (select k from kk)::int as k, round(avg(x::double / d), 6) as avg_overlap from xd")
def avg_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.avg_overlap(*lists(spark, sf_dir)), "avg_overlap")


@key("overlap_at_k", ctes(*LISTS) + " select k::int as k, x::bigint as n_common, round(x::double / k, 6) as overlap from sums, kk")
def overlap_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.overlap_at(*lists(spark, sf_dir)), "overlap")


@key("kendall_tau", ctes(*LISTS, ("pp", "select a.j as j1, b.j as j2 from met a join met b on a.i < b.i"), ("cd", "select count(*) filter (where j1 < j2) as c, count(*) filter (where j1 > j2) as d from pp")) + " select (select count(*) from met)::bigint as n_items, c::bigint as concordant, d::bigint as discordant, round((c - d)::double / (c + d), 6) as tau from cd")
def kendall_tau(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.kendall_tau(*lists(spark, sf_dir)), "tau")


@key("score_l1", ctes(*APPROX, *EXACT_NOW, ("gap", f"select abs(a.score - y.score) as g, y.score as s from approx a join y{ROUNDS} y on y.id = a.id")) + " select round(sum(g), 6) as l1, round(max(g), 6) as linf, round(avg(g / abs(s)), 6) as mean_relative from gap")
def score_l1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.score_error(approximate(spark, sf_dir), exact_now(spark, sf_dir)), "l1", "linf", "mean_relative")


@key("rank_shift", ctes(*APPROX, *EXACT_NOW, ("la", "select id, row_number() over (order by round(score, 9) desc, id) as r from approx"), ("lb", f"select id, row_number() over (order by round(score, 9) desc, id) as r from y{ROUNDS}")) + " select max(abs(a.r - b.r))::bigint as max_shift, round(avg(abs(a.r - b.r)), 6) as mean_shift from la a join lb b on a.id = b.id")
def rank_shift(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.rank_shift(global_rank(approximate(spark, sf_dir)), global_rank(exact_now(spark, sf_dir))), "mean_shift")


#: A run table (set_id, metric, query, value) of the events: sets are groups of users, queries days, and kinds of events measures.
_KIND = "case event_type when 'view' then 'rbo' when 'click' then 'speedup' else 'edge_ratio' end"
RUNS_SQL = f"select user_id % 9 + 1 as set_id, {_KIND} as metric, dayofmonth(ts)::int as query, sum(value::decimal(18,6))::double / count(*) as value from events where event_type in ('view', 'click', 'purchase') group by 1, 2, 3"


def runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").where("event_type in ('view', 'click', 'purchase')")
    by = [(F.col("user_id") % 9 + 1).alias("set_id"), F.expr(_KIND).alias("metric"), F.dayofmonth("ts").alias("query")]
    return e.groupBy(*by).agg((F.sum(F.col("value").cast("decimal(18,6)")).cast("double") / F.count("*")).alias("value"))


@key("best_worst_sets", f"with r as ({RUNS_SQL}), m as (select metric, set_id, avg(value) as mean from r group by 1, 2), p as (select *, row_number() over (partition by metric order by round(mean, 9) desc, set_id) as b, row_number() over (partition by metric order by round(mean, 9), set_id) as w from m) "
    "select metric, set_id, round(mean, 6) as mean, 'best' as side, b::int as place from p where b <= 3 union all select metric, set_id, round(mean, 6), 'worst', w::int from p where w <= 3")
def best_worst_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.best_worst(runs(spark, sf_dir)), "mean")


@key("measure_series", f"with r as ({RUNS_SQL}) select set_id, metric, query, round(value, 6) as value from r union all select distinct set_id, metric, 0::int, 1.0::double from r where metric = 'rbo'")
def measure_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(measures.series(runs(spark, sf_dir)), "value")


@key("work_saved", ctes(*APPROX) + f" select 1::int as query, round(((select count(*) from hot) + 1)::double / (select count(*) from v1), 6) as vertex_ratio, round(((select count(*) from inner_) + (select sum(n_edges) from cold))::double / (select count(*) from e1), 6) as edge_ratio, round(((select count(*) from inner_) * {ROUNDS} + (select sum(n_edges) from cold))::double / ((select count(*) from e1) * {ROUNDS}), 6) as processed_share")
def work_saved(spark: SparkSession, sf_dir: str) -> DataFrame:
    from hotgraph.catalog.core import point

    at, built = point(spark, sf_dir), summary(spark, sf_dir)
    log = spark.createDataFrame(
        [(1, built.hot.count(), at.vertices.count(), built.inner.count(), built.inflow.agg(F.sum("n_edges")).first()[0] or 0, at.now.count())],
        "query int, n_hot bigint, n_vertices bigint, inner_edges bigint, boundary_edges bigint, n_edges bigint",
    )
    return _r(measures.work_saved(log, P.iterations), "vertex_ratio", "edge_ratio", "processed_share")
