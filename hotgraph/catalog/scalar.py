"""Scalar functions on text, dates, numbers, arrays, maps, structs and JSON."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import GRAPH_SQL, key
from hotgraph.catalog.graphs import graph
from hotgraph.functions.expressions import influence_budget, stable_key
from hotgraph.sources import tables
from hotgraph.sources.tables import table as _T


@key("str_url_host", "select page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, lower(split_part(url, '/', 4)) as first from pages")
def str_url_host(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), F.lower(F.split_part("url", F.lit("/"), F.lit(4))).alias("first"))


@key("str_regexp_links", "select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) as href from pages")
def str_regexp_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("href"))


@key("str_case_trim_pad", "select p_partkey, upper(p_name) as up, rtrim(ltrim('  ' || p_type || ' ')) as trimmed, lpad(p_partkey::varchar, 8, '0') as padded, length(p_name)::int as n from part")
def str_case_trim_pad(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "part").select(
        "p_partkey", F.upper("p_name").alias("up"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("trimmed"),
        F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"), F.length("p_name").alias("n"),
    )


@key("str_split_explode", "select w as word, count(*)::bigint as n from (select unnest(string_split(p_name, ' ')) as w from part) group by w")
def str_split_explode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "part").select(F.explode(F.split("p_name", " ")).alias("word")).groupBy("word").agg(F.count("*").alias("n"))


@key("str_md5_key", f"select src, dst, md5(src::varchar || '-' || dst::varchar || '-42') as key from ({GRAPH_SQL['social_urgent']})")
def str_md5_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph(spark, sf_dir, "social_urgent").select("src", "dst", stable_key("src", "dst").alias("key"))


@key("str_levenshtein", "select distinct a.p_name as a, b.p_name as b, levenshtein(a.p_name, b.p_name)::int as d from (select distinct p_name from part) a join (select distinct p_name from part) b on a.p_name < b.p_name")
def str_levenshtein(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = _T(spark, sf_dir, "part").select("p_name").distinct()
    other = names.select(F.col("p_name").alias("b"))
    return names.select(F.col("p_name").alias("a")).join(F.broadcast(other), F.col("a") < F.col("b")).withColumn("d", F.levenshtein("a", "b"))  # a few names


@key("date_trunc_month", "select date_trunc('month', o_orderdate)::timestamp as month, round(sum(o_totalprice::decimal(18,6)), 4)::double as total from orders group by 1")
def date_trunc_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    month = F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")
    return _T(spark, sf_dir, "orders").groupBy(month).agg(F.round(F.sum(F.col("o_totalprice").cast("decimal(18,6)")), 4).cast("double").alias("total"))


@key("date_diff_add", "select l_orderkey, l_linenumber, l_partkey, date_diff('day', o_orderdate::date, l_shipdate::date)::int as days, (o_orderdate::date + 30)::date as due from lineitem join orders on l_orderkey = o_orderkey")
def date_diff_add(spark: SparkSession, sf_dir: str) -> DataFrame:
    met = _T(spark, sf_dir, "lineitem").join(_T(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return met.select("l_orderkey", "l_linenumber", "l_partkey", F.date_diff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).alias("days"), F.date_add(F.to_date("o_orderdate"), 30).alias("due"))


@key("date_parts", "select o_orderkey, year(o_orderdate)::int as y, quarter(o_orderdate)::int as q, month(o_orderdate)::int as m, dayofmonth(o_orderdate)::int as d, (dayofweek(o_orderdate) + 1)::int as dow from orders")
def date_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return _T(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.quarter(d).alias("q"), F.month(d).alias("m"), F.dayofmonth(d).alias("d"), F.dayofweek(d).alias("dow"))


@key("epoch_roundtrip", "select event_id, epoch_us(ts)::bigint as us, make_timestamp(epoch_us(ts)) as again from events")
def epoch_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = tables.events(spark, sf_dir).select("event_id", F.unix_micros("ts").alias("us"))
    return e.select("event_id", "us", tables.zoneless(F.timestamp_micros("us")).alias("again"))


@key("math_round_log_pow", "select event_id, round(ln(value + 1), 6) as l, round(pow(value, 1.5), 4) as p, round(sqrt(value), 6) as s, floor(value)::bigint as f from events")
def math_round_log_pow(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    return _T(spark, sf_dir, "events").select("event_id", F.round(F.log(v + 1), 6).alias("l"), F.round(F.pow(v, F.lit(1.5)), 4).alias("p"), F.round(F.sqrt(v), 6).alias("s"), F.floor(v).alias("f"))


@key("math_safe_divide", "select event_id, round(value / nullif(user_id % 3, 0), 6) as ratio from events")
def math_safe_divide(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "events").select("event_id", F.round(F.try_divide("value", F.col("user_id") % 3), 6).alias("ratio"))


#: Score, degree and mean of each event, rows outside the formula's domain among them; delta is 0.5.
_FACTS = "event_id, value - 1 as s, user_id % 5 as d, 0.5D + event_id % 8 as m"


@key("math_budget_formula", f"select event_id, s, d, m, round(case when d > 0 and s > 0 then case when m > 1 then ln(m * s / (0.5 * d)) / ln(m) when s >= 0.5 * d then 1.0 else 0.0 end end, 6) as budget from (select {_FACTS.replace('0.5D', '0.5::double')} from events)")
def math_budget_formula(spark: SparkSession, sf_dir: str) -> DataFrame:
    facts = _T(spark, sf_dir, "events").selectExpr(*_FACTS.split(", "))
    return facts.withColumn("budget", F.round(influence_budget("s", "d", "m", 0.5), 6))


@key("arr_adjacency", f"select src, string_agg(dst::varchar, ',' order by dst) as near from ({GRAPH_SQL['social_urgent']}) group by src")
def arr_adjacency(spark: SparkSession, sf_dir: str) -> DataFrame:
    near = F.array_join(F.transform(F.array_sort(F.collect_list("dst")), lambda x: x.cast("string")), ",")
    return graph(spark, sf_dir, "social_urgent").groupBy("src").agg(near.alias("near"))


@key("arr_hof_transform_filter_aggregate", "select user_id, round(sum(round(value * 2, 4)) filter (where value > 1), 4) as total, max(value) as most from events group by user_id")
def arr_hof(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = _T(spark, sf_dir, "events").groupBy("user_id").agg(F.array_sort(F.collect_list("value")).alias("v"))
    big = F.transform(F.filter("v", lambda x: x > 1), lambda x: F.round(x * 2, 4))
    total = F.when(F.size(big) > 0, F.round(F.aggregate(big, F.lit(0.0), lambda a, x: a + x), 4))
    return held.select("user_id", total.alias("total"), F.array_max("v").alias("most"))


@key("arr_set_ops", "with a as (select p_brand, list(distinct p_size) as x from part where p_type = 'ECONOMY' group by 1), b as (select p_brand, list(distinct p_size) as y from part where p_type = 'STANDARD' group by 1) select a.p_brand, len(list_intersect(x, y))::int as both, len(list_distinct(list_concat(x, y)))::int as any from a join b on a.p_brand = b.p_brand")
def arr_set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = lambda kind, name: _T(spark, sf_dir, "part").where(F.col("p_type") == kind).groupBy("p_brand").agg(F.collect_set("p_size").alias(name))
    return sizes("ECONOMY", "x").join(sizes("STANDARD", "y"), "p_brand").select("p_brand", F.size(F.array_intersect("x", "y")).alias("both"), F.size(F.array_union("x", "y")).alias("any"))


@key("map_from_groups", "select user_id, event_type, count(*)::bigint as n from events group by 1, 2")
def map_from_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = _T(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("event_type", "n"))


@key("struct_access", "select c_custkey, c_name as name, c_acctbal as balance from customer where c_acctbal > 5000")
def struct_access(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = _T(spark, sf_dir, "customer").select("c_custkey", F.struct(F.col("c_name").alias("name"), F.col("c_acctbal").alias("balance")).alias("s"))
    return c.where("s.balance > 5000").select("c_custkey", "s.name", "s.balance")


@key("arr_cosine", "with v as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings), q as (select e from v where vec_id = 0), c as (select v.vec_id, list_dot_product(v.e, q.e) / sqrt(list_dot_product(v.e, v.e) * list_dot_product(q.e, q.e)) as c from v, q where vec_id <> 0) select vec_id, round(c, 6) as cosine from c order by c desc, vec_id limit 10")
def arr_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = _T(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    q = v.where("vec_id = 0").select(F.col("e").alias("q"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    c = dot("e", "q") / F.sqrt(dot("e", "e") * dot("q", "q"))
    found = v.where("vec_id <> 0").crossJoin(F.broadcast(q)).select("vec_id", c.alias("c"))  # one query row
    return found.orderBy(F.col("c").desc(), "vec_id").limit(10).select("vec_id", F.round("c", 6).alias("cosine"))


@key("json_extract", "select event_id, (props->>'$.k')::int as k from events where (props->>'$.k')::int > 50")
def json_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _T(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return e.where("k > 50")


@key("json_from_schema", "select event_type, round(avg((props->>'$.k')::int), 6) as mean_k, max((props->>'$.k')::int)::int as max_k from events group by 1")
def json_from_schema(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _T(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int").alias("p"))
    return e.groupBy("event_type").agg(F.round(F.avg("p.k"), 6).alias("mean_k"), F.max("p.k").alias("max_k"))


@key("json_to", """select n_nationkey, '{"id":' || n_nationkey || ',"name":"' || n_name || '"}' as doc from nation""")
def json_to(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _T(spark, sf_dir, "nation").select("n_nationkey", F.to_json(F.struct(F.col("n_nationkey").alias("id"), F.col("n_name").alias("name"))).alias("doc"))
