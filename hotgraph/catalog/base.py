"""Registry of queries and their oracles, and SQL text that several oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from hotgraph.storage import on_release

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_memo: dict[tuple, object] = {}
on_release(_memo.clear)


def key(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(name)
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return put


def once(spark: SparkSession, *what: object, make: Callable[[], object]) -> object:
    """What several queries of one session start from, made once."""
    at = (spark.sparkContext.applicationId, *what)
    if at not in _memo:
        _memo[at] = make()
    return _memo[at]


def held(spark: SparkSession, *what: object) -> object | None:
    """What once() has made of it, if it has."""
    return _memo.get((spark.sparkContext.applicationId, *what))


def _lead(table: str, value: str, part: str, order: str, where: str = "") -> str:
    over = f"{'partition by ' + part + ' ' if part else ''}order by {order}"
    return (
        f"select distinct src, dst from (select {value} as src, lead({value}) over ({over}) as dst from {table} {where}) "
        "where dst is not null and src <> dst"
    )


#: Edges of each graph in SQL.
GRAPH_SQL = {
    "copurchase": _lead("lineitem", "l_partkey", "l_orderkey", "l_linenumber, l_partkey, l_suppkey"),
    "social_urgent": _lead(
        "orders join customer on o_custkey = c_custkey", "c_custkey", "c_nationkey", "o_orderdate, o_orderkey", "where o_orderpriority = '1-URGENT'"
    ),
    "web_site": (
        "select distinct ('0x' || substr(md5(host), 1, 15))::bigint as src, ('0x' || substr(md5(path), 1, 15))::bigint as dst from "
        "(select regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) as path from pages) "
        "where host <> path"
    ),
    "user_next": _lead("events", "user_id", "", "ts, event_id"),
    "purchase_next": _lead("events", "user_id", "", "ts, event_id", "where event_type = 'purchase'"),
    "order_chain": _lead("orders", "o_orderkey", "o_custkey", "o_orderdate, o_orderkey"),
    "cust_part": "select distinct o_custkey as src, l_partkey + 1000000000000 as dst from orders join lineitem on o_orderkey = l_orderkey",
    "supplier_co": (
        "select distinct a.l_suppkey as src, b.l_suppkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey "
        "where a.l_suppkey <> b.l_suppkey"
    ),
}
for _new, _old in (("social_symmetric", "social_urgent"), ("web_circulating", "web_site")):
    GRAPH_SQL[_new] = f"with o as ({GRAPH_SQL[_old]}) select src, dst from o union select dst, src from o"


def ctes(*parts: tuple[str, str]) -> str:
    return "with recursive " + ",\n".join(f"{name} as materialized ({text})" for name, text in parts)


def ends_sql(edges: str) -> str:
    return f"select src as id from {edges} union select dst from {edges}"


def loop_sql(p: str, links: str, base: str, rounds: int, beta: float = 0.85) -> list[tuple[str, str]]:
    """Rounds {p}0..{p}N of the ranking loop; links(src, dst, weight), base(id, fixed, score)."""
    out = [(f"{p}0", f"select id, score from {base}")]
    for k in range(1, rounds + 1):
        out.append((
            f"{p}{k}",
            f"select b.id, b.fixed + {beta} * coalesce(g.got, 0) as score from {base} b left join (select l.dst, sum(s.score * l.weight) as got "
            f"from {links} l join {p}{k - 1} s on s.id = l.src group by l.dst) g on g.dst = b.id",
        ))
    return out


def weighted_sql(edges: str) -> str:
    return f"select e.src, e.dst, 1.0::double / d.n as weight from {edges} e join (select src, count(*) as n from {edges} group by src) d on d.src = e.src"


def exact_sql(p: str, edges: str, verts: str, rounds: int, beta: float = 0.85) -> list[tuple[str, str]]:
    """CTEs of the exact ranking of edges over verts; the last is {p}{rounds}."""
    return [
        (f"{p}links", weighted_sql(edges)),
        (f"{p}base", f"select id, {1 - beta:.17g}::double as fixed, 1.0::double as score from {verts}"),
        *loop_sql(p, f"{p}links", f"{p}base", rounds, beta),
    ]
