"""Relational operators around the method: sources and sinks, projection, joins, aggregation, windows, sets, subqueries."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hotgraph.catalog.base import GRAPH_SQL, ctes, ends_sql, exact_sql, key
from hotgraph.catalog.graphs import graph
from hotgraph.operators import joins
from hotgraph.operators.iterate import rank_exact
from hotgraph.operators.ranks import global_rank
from hotgraph.sources import tables
from hotgraph.sources.tables import table

_C = GRAPH_SQL["copurchase"]
_T = table


# Columns and windows are made where they are used: without a session there are none.


def _rev():  # noqa: ANN202
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


def _money(c):  # noqa: ANN001, ANN202
    """A sum of money that does not depend on the order of rows."""
    return F.round(F.sum(c.cast("decimal(18,6)")), 4).cast("double")


def _msql(x: str) -> str:
    return f"round(sum(({x})::decimal(18,6)), 4)::double"


# Sources and sinks ----------------------------------------------------------------------------------------------------


@key("scan_parquet_pruned", "select l_orderkey, l_partkey, l_quantity from lineitem where l_quantity < 10")
def scan_parquet_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "lineitem").where("l_quantity < 10").select("l_orderkey", "l_partkey", "l_quantity")


def _format_key(kind: str) -> None:
    @key(f"scan_{kind}_roundtrip", "select n_nationkey, n_name, r_name from nation join region on n_regionkey = r_regionkey")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = _T(spark, sf_dir, "nation").join(_T(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
        return tables.round_trip(df.select("n_nationkey", "n_name", "r_name"), kind, "nations")


for _kind in ("csv", "json", "orc"):
    _format_key(_kind)


@key("scan_edge_list_text", _C)
def scan_edge_list_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = tables.scratch(spark, "edges")
    lines = graph(spark, sf_dir, "copurchase").select(F.concat_ws("\t", "src", "dst").alias("value"))
    lines.union(spark.createDataFrame([("not an edge",), ("1\t2\t3",), ("x\t4",)], "value string")).write.text(path)
    return tables.edge_list(spark, path)


@key("scan_edge_list_malformed", ctes(("e", _C)) + " select (count(*) + 3)::bigint as lines, count(*)::bigint as good, 3::bigint as bad from e")
def scan_edge_list_malformed(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = tables.scratch(spark, "edges")
    lines = graph(spark, sf_dir, "copurchase").select(F.concat_ws("\t", "src", "dst").alias("value"))
    lines.union(spark.createDataFrame([("not an edge",), ("1\t2\t3",), ("x\t4",)], "value string")).write.text(path)
    return tables.malformed(spark, path)


@key("sink_parquet_partitioned", "select o_orderkey, o_totalprice from orders where year(o_orderdate) = 1997")
def sink_parquet_partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = tables.scratch(spark, "orders")
    dated = _T(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice", F.year("o_orderdate").alias("y"))
    dated.repartition("y").write.partitionBy("y").parquet(path)
    return spark.read.parquet(path).where("y = 1997").select("o_orderkey", "o_totalprice")


@key("sink_bucketed_edges", ctes(("e", _C)) + " select a.src, count(*)::bigint as n from e a join e b on a.src = b.src group by a.src")
def sink_bucketed_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    name = f"hot_edges_{uuid.uuid4().hex}"
    b = tables.bucketed(graph(spark, sf_dir, "copurchase"), name)
    other = tables.bucketed(graph(spark, sf_dir, "copurchase"), f"{name}_too").select("src")
    return b.select("src").hint("merge").join(other, "src").groupBy("src").agg(F.count("*").alias("n"))


# Projection and filter ------------------------------------------------------------------------------------------------


@key("filter_range", "select l_orderkey, l_linenumber, l_discount from lineitem where l_shipdate >= timestamp '1996-01-01' and l_shipdate < timestamp '1997-01-01' and l_discount between 0.02 and 0.05")
def filter_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = _T(spark, sf_dir, "lineitem")
    return li.where("l_shipdate >= timestamp_ntz '1996-01-01' and l_shipdate < timestamp_ntz '1997-01-01' and l_discount between 0.02D and 0.05D").select("l_orderkey", "l_linenumber", "l_discount")


@key("filter_in_like", "select p_partkey, p_name, p_type from part where p_type in ('ECONOMY', 'STANDARD') and p_name like '%ring'")
def filter_in_like(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "part").where(F.col("p_type").isin("ECONOMY", "STANDARD") & F.col("p_name").like("%ring")).select("p_partkey", "p_name", "p_type")


@key("project_exprs", "select l_orderkey, l_linenumber, (l_extendedprice::decimal(12,2) * (1 - l_discount::decimal(4,2)))::double as revenue, (l_extendedprice::decimal(12,2) * (1 - l_discount::decimal(4,2)) * (1 + l_tax::decimal(4,2)))::double as charge from lineitem")
def project_exprs(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = lambda c, p: F.col(c).cast(f"decimal({p},2)")
    revenue = d("l_extendedprice", 12) * (1 - d("l_discount", 4))
    return _T(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", revenue.cast("double").alias("revenue"), (revenue * (1 + d("l_tax", 4))).cast("double").alias("charge")
    )


@key("case_when", "select case when l_quantity < 10 then 'small' when l_quantity < 30 then 'medium' else 'large' end as band, count(*)::bigint as n from lineitem group by 1")
def case_when(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = F.col("l_quantity")
    band = F.when(q < 10, "small").when(q < 30, "medium").otherwise("large")
    return _T(spark, sf_dir, "lineitem").groupBy(band.alias("band")).agg(F.count("*").alias("n"))


@key("null_semantics", "select count(*)::bigint as n, count(quality)::bigint as n_rated, count(*) filter (where quality is not distinct from toxic)::bigint as same, count(*) filter (where coalesce(quality, -1) = -1)::bigint as unrated from documents d left join labels l on d.doc_id = l.doc_id")
def null_semantics(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = _T(spark, sf_dir, "documents").select("doc_id").join(_T(spark, sf_dir, "labels"), "doc_id", "left")
    return d.agg(
        F.count("*").alias("n"), F.count("quality").alias("n_rated"), F.count_if(F.col("quality").eqNullSafe(F.col("toxic"))).alias("same"),
        F.count_if(F.coalesce("quality", F.lit(-1)) == -1).alias("unrated"),
    )


# Joins ----------------------------------------------------------------------------------------------------------------


@key("join_inner_broadcast", f"select n_name, count(*)::bigint as n_orders, {_msql('o_totalprice')} as total from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by n_name")
def join_inner_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    met = _T(spark, sf_dir, "orders").join(_T(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    met = met.join(F.broadcast(_T(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 rows
    return met.groupBy("n_name").agg(F.count("*").alias("n_orders"), _money(F.col("o_totalprice")).alias("total"))


_PRIORITY = f"select o_orderpriority, {_msql('l_extendedprice * (1 - l_discount)')} as revenue, count(*)::bigint as n from orders join lineitem on o_orderkey = l_orderkey group by o_orderpriority"


def _hint_key(name: str, hint: str) -> None:
    @key(name, _PRIORITY)
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        met = _T(spark, sf_dir, "lineitem").join(_T(spark, sf_dir, "orders").hint(hint), F.col("o_orderkey") == F.col("l_orderkey"))
        return met.groupBy("o_orderpriority").agg(_money(_rev()).alias("revenue"), F.count("*").alias("n"))


_hint_key("join_sort_merge", "merge")
_hint_key("join_shuffle_hash", "shuffle_hash")


def _outer_key(kind: str, sql_kind: str) -> None:
    @key(f"join_{kind}", f"select d.lang, l.quality, count(*)::bigint as n, count(d.doc_id)::bigint as n_docs, count(l.doc_id)::bigint as n_labels from documents d {sql_kind} join labels l on d.doc_id = l.doc_id and l.quality = 1 group by d.lang, l.quality")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = _T(spark, sf_dir, "documents").select(F.col("doc_id").alias("d"), "lang")
        lab = _T(spark, sf_dir, "labels").select(F.col("doc_id").alias("l"), "quality")
        met = d.join(lab, (F.col("d") == F.col("l")) & (F.col("quality") == 1), kind)
        return met.groupBy("lang", "quality").agg(F.count("*").alias("n"), F.count("d").alias("n_docs"), F.count("l").alias("n_labels"))


for _k, _s in (("left", "left"), ("right", "right"), ("full", "full")):
    _outer_key(_k, _s)


def _exists_key(name: str, kind: str, word: str) -> None:
    @key(name, f"select c_custkey, c_name from customer where {word} exists (select 1 from orders where o_custkey = c_custkey and o_orderpriority = '1-URGENT')")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        urgent = _T(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'").select("o_custkey")
        return _T(spark, sf_dir, "customer").join(urgent, F.col("c_custkey") == F.col("o_custkey"), kind).select("c_custkey", "c_name")


_exists_key("join_semi", "left_semi", "")
_exists_key("join_anti", "left_anti", "not")


@key("join_theta", "select a.s_suppkey as low, b.s_suppkey as high from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_acctbal < b.s_acctbal")
def join_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = _T(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    other = s.toDF("high", "nation", "bal")
    return s.join(other, (F.col("s_nationkey") == F.col("nation")) & (F.col("s_acctbal") < F.col("bal"))).select(F.col("s_suppkey").alias("low"), "high")


#: Value bands of events: name, from, to (not included).
BANDS = [("tiny", 0.0, 1.0), ("small", 1.0, 5.0), ("middle", 5.0, 20.0), ("large", 20.0, 50.0), ("huge", 50.0, 1000.0)]
_BANDS_SQL = "(values " + ", ".join(f"('{n}', {a}::double, {b}::double)" for n, a, b in BANDS) + ") b(band, low, high)"


@key("join_range", f"select band, count(*)::bigint as n from events join {_BANDS_SQL} on value >= low and value < high group by band")
def join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    bands = spark.createDataFrame(BANDS, "band string, low double, high double")
    return joins.range_join(_T(spark, sf_dir, "events").select("event_id", "value"), bands, "value", "low", "high", 10.0).groupBy("band").agg(F.count("*").alias("n"))


@key("join_interval", "select c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts > c.ts and p.ts <= c.ts + interval 1 hour")
def join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _T(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    clicks = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", "ts")
    buys = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("at"))
    return joins.interval_join(clicks, buys, "user_id", "ts", "at", 3600).select("click", "purchase")


@key("join_asof_last_event", "select p.event_id as purchase, v.event_id as view from (select * from events where event_type = 'purchase') p asof left join (select * from events where event_type = 'view') v on p.user_id = v.user_id and p.ts > v.ts")
def join_asof_last_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _T(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    left = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase"))
    right = e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view"))
    return joins.asof_join(left, right, "user_id", "ts").select("purchase", "view")


@key("join_cross_small", "select r_name, event_type from region cross join (select distinct event_type from events)")
def join_cross_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    kinds = _T(spark, sf_dir, "events").select("event_type").distinct()
    return _T(spark, sf_dir, "region").select("r_name").crossJoin(F.broadcast(kinds))  # a few kinds


@key("join_skew_salted", f"select p_brand, count(*)::bigint as n, {_msql('l_extendedprice')} as total from (select *, case when l_partkey % 3 = 0 then 0 else l_partkey end as k from lineitem) join part on k = p_partkey group by p_brand")
def join_skew_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A third of all rows carry one key; it is dealt over salts, and its one partner is copied to each."""
    li = _T(spark, sf_dir, "lineitem").select(F.when(F.col("l_partkey") % 3 == 0, 0).otherwise(F.col("l_partkey")).cast("bigint").alias("k"), "l_extendedprice")
    parts = _T(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"), "p_brand")
    return joins.salted_join(li, parts, "k", 8).groupBy("p_brand").agg(F.count("*").alias("n"), _money(F.col("l_extendedprice")).alias("total"))


@key("join_lateral_topk", "select c_custkey, o_orderkey from customer, lateral (select o_orderkey from orders where o_custkey = c_custkey order by o_totalprice desc, o_orderkey limit 2)")
def join_lateral_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two dearest orders of each customer, placed by a window: Spark's own lateral limit reads them in no order once
    they have been shuffled.
    """
    c, o = _T(spark, sf_dir, "customer").select("c_custkey"), _T(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", "o_totalprice")
    by = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc_nulls_last(), F.col("o_orderkey").asc_nulls_last())
    few = o.withColumn("place", F.row_number().over(by)).where("place <= 2")
    return c.join(few, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


@key("join_null_safe", "with n as (select d.doc_id, l.quality from documents d left join labels l on d.doc_id = l.doc_id) select k.name, count(*)::bigint as n from n join (values ('none', null::int), ('low', 0), ('high', 1)) k(name, q) on n.quality is not distinct from k.q group by k.name")
def join_null_safe(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = _T(spark, sf_dir, "documents").select("doc_id").join(_T(spark, sf_dir, "labels"), "doc_id", "left").select("quality")
    kinds = spark.createDataFrame([("none", None), ("low", 0), ("high", 1)], "name string, q int")
    return n.join(F.broadcast(kinds), F.col("quality").eqNullSafe(F.col("q"))).groupBy("name").agg(F.count("*").alias("n"))


@key("join_star_5way", f"select r_name, year(o_orderdate)::int as y, {_msql('l_extendedprice * (1 - l_discount)')} as revenue from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2")
def join_star_5way(spark: SparkSession, sf_dir: str) -> DataFrame:
    met = _T(spark, sf_dir, "lineitem").join(_T(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    met = met.join(_T(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(_T(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    met = met.join(_T(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return met.groupBy("r_name", F.year("o_orderdate").alias("y")).agg(_money(_rev()).alias("revenue"))


# Aggregation ----------------------------------------------------------------------------------------------------------


@key("agg_hash", f"select l_returnflag, l_linestatus, sum(l_quantity)::double as sum_qty, {_msql('l_extendedprice')} as sum_price, round(avg(l_discount), 6) as avg_disc, count(*)::bigint as n from lineitem where l_shipdate <= timestamp '2001-06-01' group by 1, 2")
def agg_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "lineitem").where("l_shipdate <= timestamp_ntz '2001-06-01'").groupBy("l_returnflag", "l_linestatus").agg(
        F.sum("l_quantity").alias("sum_qty"), _money(F.col("l_extendedprice")).alias("sum_price"), F.round(F.avg("l_discount"), 6).alias("avg_disc"), F.count("*").alias("n")
    )


@key("agg_sort", "select p_brand, max(p_name) as last_name, min(p_type) as first_type from part group by p_brand")
def agg_sort(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "part").groupBy("p_brand").agg(F.max("p_name").alias("last_name"), F.min("p_type").alias("first_type"))


@key("agg_partial_final", ctes(("e", _C), ("d", "select src, count(*) as n from e group by src")) + " select e.dst, round(sum(1.0::double / d.n), 6) as inflow from e join d on d.src = e.src group by e.dst")
def agg_partial_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    from hotgraph.operators.iterate import weighted

    return weighted(graph(spark, sf_dir, "copurchase")).groupBy("dst").agg(F.round(F.sum("weight"), 6).alias("inflow"))


@key("agg_distinct", "select l_suppkey, count(distinct l_partkey)::bigint as n_parts from lineitem group by 1")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("n_parts"))


@key("agg_multi_distinct", "select l_returnflag, count(distinct l_partkey)::bigint as n_parts, count(distinct l_suppkey)::bigint as n_supp from lineitem group by 1")
def agg_multi_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("n_parts"), F.countDistinct("l_suppkey").alias("n_supp"))


@key("agg_filter_clause", "select o_orderpriority, count(*) filter (where o_orderstatus = 'F')::bigint as n_f, count(*) filter (where o_totalprice > 200000)::bigint as n_big from orders group by 1")
def agg_filter_clause(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.sql("select o_orderpriority, count(*) filter (where o_orderstatus = 'F') as n_f, count(*) filter (where o_totalprice > 200000) as n_big from {o} group by 1", o=_T(spark, sf_dir, "orders"))


_BAL = "customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"


def _balances(spark: SparkSession, sf_dir: str) -> DataFrame:
    met = _T(spark, sf_dir, "customer").join(_T(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return met.join(_T(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))


def _grouping_key(name: str, clause: str) -> None:
    @key(name, f"select r_name, c_mktsegment, grouping(r_name, c_mktsegment)::bigint as g, {_msql('c_acctbal')} as total, count(*)::bigint as n from {_BAL} group by {clause}")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        text = f"select r_name, c_mktsegment, cast(grouping_id(r_name, c_mktsegment) as bigint) as g, cast(round(sum(cast(c_acctbal as decimal(18,6))), 4) as double) as total, count(*) as n from {{b}} group by {clause}"
        return spark.sql(text, b=_balances(spark, sf_dir))


_grouping_key("agg_rollup", "rollup (r_name, c_mktsegment)")
_grouping_key("agg_cube", "cube (r_name, c_mktsegment)")
_grouping_key("agg_grouping_sets", "grouping sets ((r_name, c_mktsegment), (r_name), ())")

_KINDS = ("click", "error", "purchase", "signup", "view")


@key("agg_pivot", "select (user_id % 10)::bigint as decile, " + ", ".join(f"count(*) filter (where event_type = '{k}')::bigint as \"{k}\"" for k in _KINDS) + " from events group by 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _T(spark, sf_dir, "events").groupBy((F.col("user_id") % 10).alias("decile")).pivot("event_type", list(_KINDS)).agg(F.count(F.lit(1)))
    return p.na.fill(0, list(_KINDS))


@key("agg_unpivot", "select (user_id % 10)::bigint as decile, event_type, count(*)::bigint as n from events group by 1, 2")
def agg_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return agg_pivot(spark, sf_dir).unpivot("decile", list(_KINDS), "event_type", "n").where("n > 0")


@key("agg_percentile_exact", "select o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) as p50, round(quantile_cont(o_totalprice, 0.9), 4) as p90 from orders group by 1")
def agg_percentile_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = lambda x: F.round(F.percentile("o_totalprice", F.lit(x)), 4)
    return _T(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(p(0.5).alias("p50"), p(0.9).alias("p90"))


@key("agg_stats_moments", "select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(var_pop(l_discount), 8) as var, round(corr(l_quantity, l_extendedprice), 6) as r from lineitem group by 1")
def agg_stats_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_discount"), 8).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")
    )


@key("agg_max_by", "select user_id, max_by(event_type, ts) as last_type, max(ts) as last_ts from events group by 1")
def agg_max_by(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "events").groupBy("user_id").agg(F.max_by("event_type", "ts").alias("last_type"), F.max("ts").alias("last_ts"))


@key("agg_collect_sorted", "select user_id, string_agg(distinct event_type, ',' order by event_type) as kinds from events group by 1")
def agg_collect_sorted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("kinds"))


@key("agg_approx_distinct")
def agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.countDistinct("l_partkey").alias("exact"))


@key("agg_approx_percentile")
def agg_approx_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "orders").agg(F.percentile_approx("o_totalprice", 0.5, 10000).alias("approx"), F.percentile("o_totalprice", F.lit(0.5)).alias("exact"))


@key("agg_count_min")
def agg_count_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A count-min sketch of part keys, asked for the ten most frequent."""
    from hotgraph.operators.sketches import count_min, estimate

    li = _T(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("k"))
    often = li.groupBy("k").agg(F.count("*").alias("exact")).orderBy(F.col("exact").desc(), "k").limit(10)
    return estimate(count_min(li, "k"), often, "k")


# Windows --------------------------------------------------------------------------------------------------------------


def _by():  # noqa: ANN202
    return Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")


def _ev():  # noqa: ANN202
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_over = "over (partition by o_custkey order by o_totalprice desc, o_orderkey)"
_evs = "over (partition by user_id order by ts, event_id)"


@key("win_row_number", f"select o_orderkey, row_number() {_over}::int as rn from orders")
def win_row_number(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(_by()).alias("rn"))


@key("win_rank_dense", "select p_partkey, (rank() over (partition by p_brand order by p_size))::int as r, (dense_rank() over (partition by p_brand order by p_size))::int as d from part")
def win_rank_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return _T(spark, sf_dir, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"))


@key("win_percent_rank", f"select o_orderkey, round(percent_rank() {_over}, 6) as pr, round(cume_dist() {_over}, 6) as cd from orders")
def win_percent_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "orders").select("o_orderkey", F.round(F.percent_rank().over(_by()), 6).alias("pr"), F.round(F.cume_dist().over(_by()), 6).alias("cd"))


@key("win_ntile", f"select o_orderkey, (ntile(4) {_over})::int as q from orders")
def win_ntile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "orders").select("o_orderkey", F.ntile(4).over(_by()).alias("q"))


@key("win_lag_lead", f"select event_id, lag(event_type) {_evs} as before, lead(event_id) {_evs} as next from events")
def win_lag_lead(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "events").select("event_id", F.lag("event_type").over(_ev()).alias("before"), F.lead("event_id").over(_ev()).alias("next"))


@key("win_first_last", "select event_id, first_value(value) over w as first, last_value(value) over w as last from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)")
def win_first_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = _ev().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _T(spark, sf_dir, "events").select("event_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"))


@key("win_rows_frame", "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 3 preceding and 3 following), 6) as mean7 from events")
def win_rows_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "events").select("event_id", F.round(F.avg("value").over(_ev().rowsBetween(-3, 3)), 6).alias("mean7"))


@key("win_range_frame", "select event_id, round(sum(value) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row), 4) as day_sum from events")
def win_range_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = tables.events(spark, sf_dir).withColumn("us", F.unix_micros("ts"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.round(F.sum("value").over(w), 4).alias("day_sum"))


@key("win_running_sum", f"select event_id, round(sum(value::decimal(18,6)) {_evs}, 4)::double as running from events")
def win_running_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = _ev().rowsBetween(Window.unboundedPreceding, 0)
    return _T(spark, sf_dir, "events").select("event_id", F.round(F.sum(F.col("value").cast("decimal(18,6)")).over(w), 4).cast("double").alias("running"))


@key("win_topn_per_group", f"with r as (select p_brand, p_partkey, {_msql('l_extendedprice')} as revenue from part join lineitem on p_partkey = l_partkey group by 1, 2), k as (select *, row_number() over (partition by p_brand order by revenue desc, p_partkey) as k from r) select p_brand, p_partkey, revenue, k::int as k from k where k <= 3")
def win_topn_per_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = _T(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(_money(F.col("l_extendedprice")).alias("revenue"))
    met = _T(spark, sf_dir, "part").select("p_brand", "p_partkey").join(li, F.col("p_partkey") == F.col("l_partkey"))
    w = Window.partitionBy("p_brand").orderBy(F.col("revenue").desc(), "p_partkey")
    return met.withColumn("k", F.row_number().over(w)).where("k <= 3").select("p_brand", "p_partkey", "revenue", "k")


_SESSIONS = """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts, event_id) <= interval 30 minute then 0 else 1 end as new from events),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as n from g)"""


@key("win_sessionize", _SESSIONS + " select user_id, n::bigint as session, min(ts) as start, count(*)::bigint as events from s group by 1, 2")
def win_sessionize(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _T(spark, sf_dir, "events").select("user_id", "ts", "event_id")
    gap = F.col("ts") - F.lag("ts").over(_ev()) <= F.expr("interval 30 minutes")
    s = e.withColumn("new", F.when(gap, 0).otherwise(1)).withColumn("session", F.sum("new").over(_ev().rowsBetween(Window.unboundedPreceding, 0)))
    return s.groupBy("user_id", "session").agg(F.min("ts").alias("start"), F.count("*").alias("events"))


# Sorting and top-k ----------------------------------------------------------------------------------------------------


@key("sort_multi_nulls", "select doc_id, quality, place from (select d.doc_id, l.quality, row_number() over (order by l.quality desc nulls last, d.doc_id)::int as place from documents d left join labels l on d.doc_id = l.doc_id) where place <= 100")
def sort_multi_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = _T(spark, sf_dir, "documents").select("doc_id").join(_T(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")
    order = [F.col("quality").desc_nulls_last(), F.col("doc_id").asc()]
    few = d.orderBy(*order).limit(100)
    return few.withColumn("place", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*order)))  # 100 rows


@key("topk_global", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def topk_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@key("limit_offset", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20 offset 20")
def limit_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(20).limit(20).select("o_orderkey", "o_totalprice")


@key("global_rank_distributed", ctes(("e", _C), ("v", ends_sql("e")), *exact_sql("s", "e", "v", 5)) + " select id, row_number() over (order by round(score, 9) desc, id)::bigint as rank from s5")
def global_rank_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return global_rank(rank_exact(graph(spark, sf_dir, "copurchase"), iterations=5, kernel="auto")).select("id", F.col("rank").cast("bigint").alias("rank"))


# Sets and subqueries --------------------------------------------------------------------------------------------------

_A = "select l_partkey as a, l_suppkey as b from lineitem where l_returnflag = 'A'"
_B = "select l_partkey as a, l_suppkey as b from lineitem where l_returnflag = 'R'"


def _flags(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    li = _T(spark, sf_dir, "lineitem")
    pick = lambda f: li.where(F.col("l_returnflag") == f).select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b"))
    return pick("A"), pick("R")


def _set_key(name: str, word: str, op) -> None:  # noqa: ANN001
    @key(name, f"{_A} {word} {_B}")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        return op(*_flags(spark, sf_dir))


_set_key("set_union_all", "union all", lambda a, b: a.unionAll(b))
_set_key("set_union", "union", lambda a, b: a.union(b).distinct())
_set_key("set_intersect", "intersect", lambda a, b: a.intersect(b))
_set_key("set_intersect_all", "intersect all", lambda a, b: a.intersectAll(b))
_set_key("set_except", "except", lambda a, b: a.subtract(b))
_set_key("set_except_all", "except all", lambda a, b: a.exceptAll(b))


@key("union_by_name", f"select a, b, null::varchar as note from ({_A}) union all select a, b, 'r' from ({_B})")
def union_by_name(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _flags(spark, sf_dir)
    return a.unionByName(b.select(F.lit("r").alias("note"), "b", "a"), allowMissingColumns=True)


def _sql_key(name: str, text: str, oracle: str | None = None) -> None:
    @key(name, oracle or text)
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        import re

        used = [t for t in ("orders", "lineitem", "customer", "part", "nation", "region", "labels", "documents") if re.search(rf"\b{t}\b", text)]
        filled = text
        for t in used:
            filled = re.sub(rf"\b{t}\b", f"{{{t}}}", filled)
        return spark.sql(filled, **{t: _T(spark, sf_dir, t) for t in used})


_sql_key("sub_exists", "select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_quantity > 45)")
_sql_key("sub_not_in_null", "select doc_id from labels where quality not in (select case when toxic = 1 then 0 end from labels where doc_id % 2 = 0)")
_sql_key("sub_not_in", "select p_partkey from part where p_partkey not in (select l_partkey from lineitem where l_quantity > 40)")
_sql_key("sub_scalar_correlated", "select o_orderkey from orders o where o_totalprice > (select avg(o_totalprice) * 1.5 from orders i where i.o_custkey = o.o_custkey)")
_sql_key(
    "cte_chain",
    "with big as (select o_custkey, count(*) as n from orders where o_totalprice > 300000 group by o_custkey), ranked as (select c_nationkey, max(n) as most from big join customer on o_custkey = c_custkey group by c_nationkey) select n_name, cast(most as bigint) as most from ranked join nation on c_nationkey = n_nationkey",
)
