"""Graph builders and graph statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import GRAPH_SQL, ctes, ends_sql, key, once
from hotgraph.operators import programs, stats
from hotgraph.sources.graphs import BUILDERS, ends, open_graph
from hotgraph.sources.tables import table
from hotgraph.storage import settle


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges of a graph, built once a session."""
    return once(spark, "graph", sf_dir, name, make=lambda: settle(BUILDERS[name](spark, sf_dir), name))


def _builder(name: str):  # noqa: ANN202
    return lambda spark, sf_dir: BUILDERS[name](spark, sf_dir).select("src", "dst")


for _key, _name in {
    "graph_copurchase": "copurchase", "graph_social": "social_urgent", "graph_web": "web_site", "graph_user_next": "user_next",
    "graph_purchase_next": "purchase_next", "graph_order_chain": "order_chain", "graph_bipartite": "cust_part",
    "graph_supplier_co": "supplier_co", "graph_symmetric": "social_symmetric",
}.items():
    key(_key, GRAPH_SQL[_name])(_builder(_name))

_E = ("e", GRAPH_SQL["copurchase"])
_S = ("e", GRAPH_SQL["social_urgent"])


@key("graph_knn", """
with v as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings),
n as (select vec_id, e, sqrt(list_dot_product(e, e)) as norm from v),
p as (select a.vec_id as src, b.vec_id as dst, round(list_dot_product(a.e, b.e) / (a.norm * b.norm), 9) as c from n a join n b on a.vec_id <> b.vec_id),
r as (select src, dst, row_number() over (partition by src order by c desc, dst) as k from p)
select src, dst from r where k <= 3
""")
def graph_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three nearest neighbours by cosine: blocks of vectors against blocks, the best of each block, then the best of all."""
    from hotgraph.operators.neighbours import nearest

    return nearest(table(spark, sf_dir, "embeddings"), 3).select("src", "dst")


@key("deg_out", ctes(_E, ("v", ends_sql("e"))) + " select v.id, count(e.src)::bigint as degree from v left join e on e.src = v.id group by v.id")
def deg_out(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.degrees(graph(spark, sf_dir, "copurchase"), "out")


@key("deg_in", ctes(_E, ("v", ends_sql("e"))) + " select v.id, count(e.src)::bigint as degree from v left join e on e.dst = v.id group by v.id")
def deg_in(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.degrees(graph(spark, sf_dir, "copurchase"), "in")


@key("deg_total", ctes(_E) + " select id, count(*)::bigint as degree from (select src as id from e union all select dst from e) group by id")
def deg_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.degrees(graph(spark, sf_dir, "copurchase"), "total")


@key("deg_histogram", ctes(_E, ("d", "select src, count(*) as degree from e group by src")) + " select degree::bigint as degree, count(*)::bigint as vertices from d group by degree")
def deg_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.out_degrees(graph(spark, sf_dir, "copurchase")).groupBy(F.col("out_deg").alias("degree")).agg(F.count("*").alias("vertices"))


_ALL = ("copurchase", "social_urgent", "web_site", "user_next", "purchase_next", "order_chain")


@key("mean_degree", "with recursive " + ", ".join(f"{g} as materialized ({GRAPH_SQL[g]})" for g in _ALL) + " union all ".join(
    f" select '{g}' as graph, (select count(*) from ({ends_sql(g)}))::bigint as n_vertices, count(*)::bigint as n_edges, "
    f"round(count(*)::double / (select count(*) from ({ends_sql(g)})), 6) as mean_degree from {g}" for g in _ALL))
def mean_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for g in _ALL:
        row = stats.mean_degree(graph(spark, sf_dir, g)).select(F.lit(g).alias("graph"), "n_vertices", "n_edges", F.round("mean_degree", 6).alias("mean_degree"))
        out = row if out is None else out.unionByName(row)
    return out


_W = ("e", GRAPH_SQL["web_site"])


@key("sinks", ctes(_W, ("v", ends_sql("e"))) + " select id from v where id not in (select src from e)")
def sinks(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = graph(spark, sf_dir, "web_site")
    return ends(e).join(e.select(F.col("src").alias("id")), "id", "left_anti")


@key("sources", ctes(_W, ("v", ends_sql("e"))) + " select id from v where id not in (select dst from e)")
def sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = graph(spark, sf_dir, "web_site")
    return ends(e).join(e.select(F.col("dst").alias("id")), "id", "left_anti")


@key("graph_size", ctes(_S) + f" select (select count(*) from ({ends_sql('e')}))::bigint as vertices, count(*)::bigint as edges from e")
def graph_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return open_graph(spark, sf_dir, "social_urgent").query(
        "select (select count(*) from {vertices}) as vertices, (select count(*) from {edges}) as edges"
    )


@key("reciprocity", ctes(_S) + " select count(*)::bigint as n_edges, count(b.src)::bigint as n_mutual, round(count(b.src)::double / count(*), 6) as share from e left join e b on b.src = e.dst and b.dst = e.src")
def reciprocity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.reciprocity(graph(spark, sf_dir, "social_urgent")).withColumn("share", F.round("share", 6))


@key("two_hop", ctes(_S) + " select distinct a.src, b.dst from e a join e b on a.dst = b.src where a.src <> b.dst")
def two_hop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.two_hop(graph(spark, sf_dir, "social_urgent"))


@key("triangles", ctes(_S) + " select x.src as a, x.dst as b, y.dst as c from e x join e y on x.dst = y.src join e z on z.src = y.dst and z.dst = x.src where x.src < x.dst and x.src < y.dst")
def triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.triangles(graph(spark, sf_dir, "social_urgent"))


@key("components_minlabel", ctes(_S, ("s", "select src, dst from e union select dst, src from e"), ("w", "select src as id, src as root from s union select s.dst, w.root from w join s on s.src = w.id where w.root < s.dst")).replace("w as materialized", "w as") + " select id, min(root) as component from w group by id")
def components_minlabel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return programs.connected(graph(spark, sf_dir, "social_urgent"))


@key("role_transitions", "with t as (select role, lead(role) over (partition by conv_id order by turn, text) as next_role from conversations) select role, next_role, count(*)::bigint as n from t where next_role is not null group by role, next_role")
def role_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Window

    by = Window.partitionBy("conv_id").orderBy("turn", "text")
    t = table(spark, sf_dir, "conversations").select("role", F.lead("role").over(by).alias("next_role"))
    return t.where("next_role is not null").groupBy("role", "next_role").agg(F.count("*").alias("n"))
