"""Directed graphs carried by the given tables: distinct edges without loops."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hotgraph.sources.tables import table
from hotgraph.storage import settle

#: Added to part numbers where customers and parts share one graph.
PART_OFFSET = 10**12


def edge_set(df: DataFrame, loops: bool = False) -> DataFrame:
    """Distinct (src, dst) without nulls, and without loops unless they are wanted."""
    picked = df.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst"))
    picked = picked.where("src is not null and dst is not null")
    return (picked if loops else picked.where("src <> dst")).distinct()


def ends(edges: DataFrame) -> DataFrame:
    """Vertices that edges touch."""
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def label_id(label: Column) -> Column:
    """60-bit id of a text, the same in any engine that has MD5."""
    return F.conv(F.substring(F.md5(label.cast("binary")), 1, 15), 16, 10).cast("bigint")


def with_next(df: DataFrame, value: str, order: list[str], by: list[str] | None = None, name: str = "next") -> DataFrame:
    """df with the value of the next row in the given order, within groups of by; null for the last row of each.

    Rows are dealt to ranges of (by, order), so a group of any size is many tasks; the last row of a group in a range
    meets the first in the next one through one row for each group and range. value and by are never null.
    """
    by, parts = by or [], int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = settle(df.repartitionByRange(parts, *by, *order).withColumn("_part", F.spark_partition_id()), "ordered")
    inside = F.lead(value).over(Window.partitionBy("_part", *by).orderBy(*order))
    begins = dealt.groupBy("_part", *by).agg(F.min_by(value, F.struct(*order)).alias("_first"))
    later = Window.partitionBy(*by, F.lit(0)).orderBy("_part")  # a row for each range
    after = settle(begins.select("_part", *by, F.lead("_first").over(later).alias("_after")).where("_after is not null"), "begins")
    return dealt.withColumn(name, inside).join(after, ["_part", *by], "left").withColumn(name, F.coalesce(name, "_after")).drop("_part", "_after")


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return edge_set(lines.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(by).alias("dst")))


def social_urgent(spark: SparkSession, sf_dir: str) -> DataFrame:
    urgent = table(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey", "o_custkey", "o_orderdate")
    people = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    met = urgent.join(people, F.col("o_custkey") == F.col("c_custkey")).where("c_nationkey is not null")
    chained = with_next(met.drop("o_custkey"), "c_custkey", ["o_orderdate", "o_orderkey"], ["c_nationkey"])
    return edge_set(chained.select(F.col("c_custkey").alias("src"), F.col("next").alias("dst")))


def web_site(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select(
        F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"),
        F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("path"),
    )
    return edge_set(pages.select(label_id(F.col("host")).alias("src"), label_id(F.col("path")).alias("dst")))


def _successive(events: DataFrame) -> DataFrame:
    """Edges from each event's user to the next event's user, over all events in time order."""
    chained = with_next(events.select("user_id", "ts", "event_id").where("user_id is not null"), "user_id", ["ts", "event_id"])
    return edge_set(chained.select(F.col("user_id").alias("src"), F.col("next").alias("dst")))


def user_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _successive(table(spark, sf_dir, "events"))


def purchase_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _successive(table(spark, sf_dir, "events").where("event_type = 'purchase'"))


def order_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return edge_set(orders.select(F.col("o_orderkey").alias("src"), F.lead("o_orderkey").over(by).alias("dst")))


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    met = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    return edge_set(met.select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + PART_OFFSET).alias("dst")))


def supplier_co(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").distinct()
    other = lines.select(F.col("l_orderkey").alias("o"), F.col("l_suppkey").alias("dst"))
    return edge_set(lines.join(other, F.col("l_orderkey") == F.col("o")).select(F.col("l_suppkey").alias("src"), "dst"))


def symmetric(edges: DataFrame) -> DataFrame:
    return edges.union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def social_symmetric(spark: SparkSession, sf_dir: str) -> DataFrame:
    return symmetric(social_urgent(spark, sf_dir))


def web_circulating(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The site graph with reversed edges added, so that scores circulate."""
    return symmetric(web_site(spark, sf_dir))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        copurchase, social_urgent, web_site, user_next, purchase_next, order_chain, cust_part, supplier_co,
        social_symmetric, web_circulating,
    )
}


@dataclass(frozen=True)
class Graph:
    """Edges, vertices and out-degrees of a graph; query() runs SQL over them as views."""

    edges: DataFrame
    vertices: DataFrame
    degrees: DataFrame

    def query(self, text: str, **views: DataFrame) -> DataFrame:
        return self.edges.sparkSession.sql(text, edges=self.edges, vertices=self.vertices, degrees=self.degrees, **views)


def open_graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    from hotgraph.operators.stats import out_degrees

    edges = BUILDERS[name](spark, sf_dir)
    return Graph(edges, ends(edges), out_degrees(edges))
