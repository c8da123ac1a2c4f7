"""Degrees and simple facts of a graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.sources.graphs import ends


def out_degrees(edges: DataFrame) -> DataFrame:
    """(id, out_deg) of the vertices that have edges out; all others have none."""
    return edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out_deg"))


def degrees(edges: DataFrame, kind: str = "out") -> DataFrame:
    """(id, degree) of every vertex; kind is out, in or total. One shuffle: both ends are counted together."""
    end = lambda name, n: F.struct(F.col(name).alias("id"), F.lit(n).cast("bigint").alias("n"))
    out, into = int(kind in ("out", "total")), int(kind in ("in", "total"))
    both = edges.select(F.explode(F.array(end("src", out), end("dst", into))).alias("e")).select("e.*")
    return both.groupBy("id").agg(F.sum("n").alias("degree"))


def both_degrees(edges: DataFrame) -> DataFrame:
    """(id, out_deg, in_deg) of every vertex that edges touch."""
    end = lambda name, o, i: F.struct(F.col(name).alias("id"), F.lit(o).cast("bigint").alias("o"), F.lit(i).cast("bigint").alias("i"))
    both = edges.select(F.explode(F.array(end("src", 1, 0), end("dst", 0, 1))).alias("e")).select("e.*")
    return both.groupBy("id").agg(F.sum("o").alias("out_deg"), F.sum("i").alias("in_deg"))


def degree_change(before: DataFrame, now: DataFrame, kind: str = "out") -> DataFrame:
    """(id, deg_prev, deg_now): deg_prev is null for a vertex that was not there, deg_now 0 for one without edges."""
    a = degrees(before, kind).select("id", F.col("degree").alias("deg_prev"))
    b = degrees(now, kind).select("id", F.col("degree").alias("deg_now"))
    return a.join(b, "id", "full_outer").select("id", "deg_prev", F.coalesce("deg_now", F.lit(0)).alias("deg_now"))


def roll_degrees(previous: DataFrame, added: DataFrame, removed: DataFrame, kind: str = "out") -> DataFrame:
    """(id, deg_prev, deg_now) from (id, degree) and the net changes alone: the graph is not counted again."""
    out, into = int(kind in ("out", "total")), int(kind in ("in", "total"))

    def moved(df: DataFrame, sign: int) -> DataFrame:
        end = lambda c, n: F.struct(F.col(c).alias("id"), F.lit(sign * n).cast("bigint").alias("d"))
        return df.select(F.explode(F.array(end("src", out), end("dst", into))).alias("e")).select("e.*")

    delta = moved(added, 1).union(moved(removed, -1)).groupBy("id").agg(F.sum("d").alias("d"))
    now = F.coalesce("degree", F.lit(0)) + F.coalesce("d", F.lit(0))
    return previous.join(delta, "id", "full_outer").select("id", F.col("degree").alias("deg_prev"), now.alias("deg_now"))


def mean_degree(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """One row: n_vertices, n_edges, mean_degree."""
    v = (ends(edges) if vertices is None else vertices).agg(F.count("*").alias("n_vertices"))
    e = edges.agg(F.count("*").alias("n_edges"))
    return v.crossJoin(e).withColumn("mean_degree", F.try_divide("n_edges", "n_vertices"))


def reciprocity(edges: DataFrame) -> DataFrame:
    """One row: n_edges, n_mutual, share of edges whose reverse is there too."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    mutual = edges.join(back, ["src", "dst"], "left_semi").agg(F.count("*").alias("n_mutual"))
    return edges.agg(F.count("*").alias("n_edges")).crossJoin(mutual).withColumn("share", F.try_divide("n_mutual", "n_edges"))


def two_hop(edges: DataFrame) -> DataFrame:
    """Distinct (src, dst) joined by a path of two edges, ends different."""
    nxt = edges.select(F.col("src").alias("mid"), F.col("dst").alias("to"))
    met = edges.join(nxt, F.col("dst") == F.col("mid")).where("src <> to")
    return met.select("src", F.col("to").alias("dst")).distinct()


def triangles(edges: DataFrame) -> DataFrame:
    """Directed cycles of three vertices (a, b, c), each once: a is the smallest.

    Every edge is also a row from its end of smaller degree (of equals, of smaller id) to the other, with its way. Wedges
    are formed at such lesser ends only, of which a vertex is one for few edges however large a hub it is, and closed by
    one join.
    """
    n = degrees(edges, "total")
    known = (
        edges.join(n.select(F.col("id").alias("src"), F.col("degree").alias("m")), "src")
        .join(n.select(F.col("id").alias("dst"), F.col("degree").alias("n")), "dst")
    )
    ahead = F.struct("m", "src") < F.struct("n", "dst")
    ends_ = lambda at, to: (
        F.when(ahead, F.col("src")).otherwise(F.col("dst")).alias(at), F.when(ahead, F.col("dst")).otherwise(F.col("src")).alias(to)
    )
    wedge = known.select(*ends_("low", "x"), ahead.alias("out_x")).join(known.select(*ends_("low", "y"), ahead.alias("out_y")), "low")
    # a cycle has one edge out of each vertex: low -> x and y -> low, closed by x -> y
    open_ = wedge.where("out_x and not out_y and x <> y").select("low", "x", "y")
    closed = open_.join(edges.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"])
    a = F.least("low", "x", "y")
    return closed.select(
        a.alias("a"),
        F.when(a == F.col("low"), F.col("x")).when(a == F.col("x"), F.col("y")).otherwise(F.col("low")).alias("b"),
        F.when(a == F.col("low"), F.col("y")).when(a == F.col("x"), F.col("low")).otherwise(F.col("x")).alias("c"),
    )
