"""The core methods on social_urgent (one chunk of its stream) and on copurchase."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import GRAPH_SQL, ctes, ends_sql, exact_sql, key, loop_sql, once
from hotgraph.catalog.graphs import graph
from hotgraph.operators import baselines, programs
from hotgraph.operators.iterate import power_loop, rank_exact, rank_personalised, weighted
from hotgraph.operators.ranks import top
from hotgraph.operators.selection import expand_by_influence, expand_hops, select_changed, select_hot
from hotgraph.operators.stats import degree_change, mean_degree
from hotgraph.operators.summary import Summary, build_summary, outside_total, rank_approximate, summary_ratio
from hotgraph.operators.updates import make_stream, merge_updates, net_changes
from hotgraph.plans import policies
from hotgraph.plans.session import Hooks, QuerySession
from hotgraph.schema import Params
from hotgraph.sources.graphs import ends
from hotgraph.storage import settle

ROUNDS, CHUNK, CHUNKS, GONE = 10, 11, 5, 2
P = Params(r=0.2, n=1, delta=0.5, iterations=ROUNDS)


@dataclass(frozen=True)
class Point:
    """The graph before and after the first chunk, its vertices after, and the exact scores before."""

    before: DataFrame
    updates: DataFrame
    now: DataFrame
    vertices: DataFrame
    scores: DataFrame


def point(spark: SparkSession, sf_dir: str) -> Point:
    def make() -> Point:
        before, updates = make_stream(graph(spark, sf_dir, "social_urgent"), CHUNK * CHUNKS, CHUNKS, GONE / CHUNK)
        updates = settle(updates, "updates")
        now = settle(merge_updates(before, *net_changes(updates.where("batch = 1"))), "now")
        vertices = settle(ends(before).union(ends(now)).distinct(), "vertices")
        scores = settle(rank_exact(before, iterations=ROUNDS, kernel="auto"), "scores")
        return Point(before, updates, now, vertices, scores)

    return once(spark, "point", sf_dir, make=make)


def hot(spark: SparkSession, sf_dir: str, p: Params = P) -> DataFrame:
    at = point(spark, sf_dir)
    return once(spark, "hot", sf_dir, p, make=lambda: settle(select_hot(at.now, at.before, at.scores, p), "hot"))


def summary(spark: SparkSession, sf_dir: str, p: Params = P) -> Summary:
    at = point(spark, sf_dir)
    return build_summary(at.now, hot(spark, sf_dir, p), at.scores)


def approximate(spark: SparkSession, sf_dir: str, p: Params = P) -> DataFrame:
    at = point(spark, sf_dir)
    make = lambda: settle(rank_approximate(summary(spark, sf_dir, p), at.scores, at.vertices, iterations=ROUNDS, kernel="auto"), "approximate")
    return once(spark, "approximate", sf_dir, p, make=make)


def exact_now(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return once(spark, "exact", sf_dir, make=lambda: settle(rank_exact(at.now, iterations=ROUNDS, vertices=at.vertices, kernel="auto"), "exact"))


# SQL of the same chain ------------------------------------------------------------------------------------------------


def key_sql(seed: int) -> str:
    return f"md5(src::varchar || '-' || dst::varchar || '-{seed}')"


STREAM = [
    ("g", GRAPH_SQL["social_urgent"]),
    ("adds", f"select src, dst, seq, least((seq - 1) // {CHUNK} + 1, {CHUNKS}) as batch from (select src, dst, row_number() over (order by {key_sql(42)}, src, dst) as seq from g) where seq <= {CHUNK * CHUNKS}"),
    ("e0", "select src, dst from g where (src, dst) not in (select (src, dst) from adds)"),
    ("del1", f"select src, dst from e0 order by {key_sql(42001)}, src, dst limit {GONE}"),
]
AT = [
    *STREAM,
    ("e1", "select src, dst from e0 where (src, dst) not in (select (src, dst) from del1) union select src, dst from adds where batch = 1"),
    ("v0", ends_sql("e0")), ("v1", "select id from v0 union " + ends_sql("e1")),
    ("d0", "select v0.id, count(e0.src) as n from v0 left join e0 on e0.src = v0.id group by v0.id"),
    ("d1", "select v1.id, count(e1.src) as n from v1 left join e1 on e1.src = v1.id group by v1.id"),
]
SCORED = [*AT, *exact_sql("x", "e0", "v0", ROUNDS)]


def seeds_sql(r: float) -> tuple[str, str]:
    return ("seeds", f"select d1.id, case when d0.id is null then 'new' else 'changed' end as reason from d1 left join d0 on d0.id = d1.id where d0.id is null or abs(d1.n - d0.n) > {r}::double * d0.n")


def bfs_sql(name: str, start: str, hops: int) -> list[tuple[str, str]]:
    """name(id, hop): fewest hops from any vertex of start, at most `hops`, those of start included with 0."""
    out = [(f"{name}0", f"select distinct id, 0 as hop from {start}")]
    for h in range(1, hops + 1):
        out.append((f"{name}{h}", f"select id, hop from {name}{h - 1} union all select distinct e1.dst, {h} from e1 join {name}{h - 1} f on f.id = e1.src and f.hop = {h - 1} where e1.dst not in (select id from {name}{h - 1})"))
    return [*out, (name, f"select id, hop from {name}{hops}")]


def ring_sql(n: int) -> list[tuple[str, str]]:
    return [*bfs_sql("near", "seeds", n), ("core", "select n.id, coalesce(s.reason, 'ring') as reason, n.hop from near n left join seeds s on s.id = n.id")]


#: Known facts of each vertex for the influence ring: s, deg, and the mean degree.
KNOWN = [
    ("mean", "select (select count(*) from e1)::double / (select count(*) from (" + ends_sql("e1") + ")) as m"),
    ("known", f"select d1.id, d1.n as deg, coalesce(x.score, 1.0) as s, m from d1 left join x{ROUNDS} x on x.id = d1.id, mean where d1.id in (" + ends_sql("e1") + ")"),
]


def _budget(delta: float) -> str:
    return f"ln(m * s / ({delta} * deg)) / ln(m)"


def candidate_sql(delta: float, hops: int = 8) -> list[tuple[str, str]]:
    return [
        *KNOWN, *bfs_sql("far", "core", hops),
        ("infl", f"select f.id, f.hop, {_budget(delta)} as budget from far f join known k on k.id = f.id where f.id not in (select id from core) and deg > 0 and s > 0 and f.hop > 0 and s >= {delta} * deg * pow(m, f.hop - 1)"),
    ]


HOT = [*SCORED, seeds_sql(0.2), *ring_sql(1), *candidate_sql(0.5), ("hot", "select id, reason, hop from core union all select id, 'influence', hop from infl")]
SUMMARY = [
    *HOT,
    ("aimed", f"select e.src, e.dst, d1.n as deg, x.score, e.src in (select id from hot) as inside from e1 e join d1 on d1.id = e.src left join x{ROUNDS} x on x.id = e.src where e.dst in (select id from hot)"),
    ("inner_", "select src, dst, 1.0::double / deg as weight from aimed where inside"),
    ("cold", "select dst, sum(coalesce(score, 0) / deg) as inflow, count(*) as n_edges from aimed where not inside group by dst"),
]
APPROX = [
    *SUMMARY,
    ("abase", f"select h.id, 0.15 + 0.85 * coalesce(c.inflow, 0) as fixed, coalesce(x.score, 1.0) as score from hot h left join cold c on c.dst = h.id left join x{ROUNDS} x on x.id = h.id"),
    *loop_sql("a", "inner_", "abase", ROUNDS),
    ("approx", f"select v1.id, coalesce(a.score, x.score, 0.15) as score, a.id is not null as is_hot from v1 left join a{ROUNDS} a on a.id = v1.id left join x{ROUNDS} x on x.id = v1.id"),
]
EXACT_NOW = exact_sql("y", "e1", "v1", ROUNDS)


def _r(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, 6) for n in names})


# Ranking --------------------------------------------------------------------------------------------------------------


def _exact_key(name: str, g: str, rounds: int = ROUNDS) -> None:
    @key(name, ctes(("e", GRAPH_SQL[g]), ("v", ends_sql("e")), *exact_sql("s", "e", "v", rounds)) + f" select id, round(score, 6) as score from s{rounds}")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _r(rank_exact(graph(spark, sf_dir, g), iterations=rounds), "score")


_exact_key("rank_exact", "copurchase")
_exact_key("rank_exact_social", "social_urgent")
_exact_key("rank_exact_sinks", "web_site")


@key("rank_beta_one", ctes(("e", GRAPH_SQL["copurchase"]), ("v", ends_sql("e")), *exact_sql("s", "e", "v", 5, 1.0)) + " select id, round(score, 6) as score from s5")
def rank_beta_one(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All of the score travels along edges."""
    return _r(rank_exact(graph(spark, sf_dir, "copurchase"), beta=1.0, iterations=5, kernel="auto"), "score")


@key("rank_split_hubs", ctes(("e", GRAPH_SQL["copurchase"]), ("v", ends_sql("e")), *exact_sql("s", "e", "v", 3)) + " select id, round(score, 6) as score from s3")
def rank_split_hubs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sources with over 30 links are dealt by target, and their scores sent to all tasks."""
    e = graph(spark, sf_dir, "copurchase")
    return _r(power_loop(weighted(e), ends(e), iterations=3, hub_links=30), "score")

_CO = [("e", GRAPH_SQL["copurchase"]), ("v", ends_sql("e"))]


@key("rank_local_kernel", ctes(*_CO, *exact_sql("s", "e", "v", 30)) + " select id, round(score, 6) as score from s30")
def rank_local_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """30 rounds in one task, after the links have been counted."""
    return _r(rank_exact(graph(spark, sf_dir, "copurchase"), iterations=30, kernel="auto"), "score")


@key("rank_topk", ctes(*_CO, *exact_sql("s", "e", "v", ROUNDS)) + f" select row_number() over (order by round(score, 9) desc, id)::bigint as rank, id, round(score, 6) as score from s{ROUNDS} order by round(score, 9) desc, id limit 20")
def rank_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(top(rank_exact(graph(spark, sf_dir, "copurchase"), iterations=ROUNDS, kernel="auto"), 20), "score")


@key("rank_beta_zero", ctes(*_CO) + " select id, 1.0::double as score from v")
def rank_beta_zero(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rank_exact(graph(spark, sf_dir, "copurchase"), beta=0.0, iterations=2, kernel="auto")


@key("rank_tolerance", ctes(("e", GRAPH_SQL["social_urgent"]), ("v", ends_sql("e")), *exact_sql("s", "e", "v", 150)) + " select id, round(score, 6) as score from s150")
def rank_tolerance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds until the scores move by at most 1e-9 in all."""
    return _r(rank_exact(graph(spark, sf_dir, "social_urgent"), iterations=200, tol=1e-9, kernel="auto"), "score")


@key("rank_dangling", ctes(("e", GRAPH_SQL["web_site"]), ("v", ends_sql("e")), ("w", "select e.src, e.dst, 1.0::double / d.n as weight from e join (select src, count(*) as n from e group by src) d on d.src = e.src"),
    ("s0", "select id, 1.0::double as score from v"),
    *((f"s{k}", f"select v.id, 0.15 + 0.85 * coalesce(g.got, 0) + 0.85 * z.spread as score from v left join (select w.dst, sum(s.score * w.weight) as got from w join s{k - 1} s on s.id = w.src group by w.dst) g on g.dst = v.id, (select sum(score) / (select count(*) from v) as spread from s{k - 1} where id not in (select src from e)) z") for k in range(1, 6))) + " select id, round(score, 6) as score from s5")
def rank_dangling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(rank_exact(graph(spark, sf_dir, "web_site"), iterations=5, dangling="redistribute"), "score")


@key("rank_personalised", ctes(*_CO, ("links", "select e.src, e.dst, 1.0::double / d.n as weight from e join (select src, count(*) as n from e group by src) d on d.src = e.src"),
    ("base", "select id, 0.15 * case when id % 10 = 0 then 1.0 else 0.0 end as fixed, 1.0::double as score from v"), *loop_sql("s", "links", "base", ROUNDS)) + f" select id, round(score, 6) as score from s{ROUNDS}")
def rank_personalised_(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = graph(spark, sf_dir, "copurchase")
    restart = ends(e).where("id % 10 = 0").select("id", F.lit(1.0).alias("share"))
    return _r(rank_personalised(e, restart, iterations=ROUNDS, kernel="auto"), "score")


@key("rank_weighted", ctes(("o", "select o_custkey as c, l_partkey + 1000000000000 as p, sum(l_quantity) as q from orders join lineitem on o_orderkey = l_orderkey group by 1, 2"),
    ("e", "select c as src, p as dst, q from o union all select p, c, q from o"), ("v", ends_sql("e")), ("links", "select e.src, e.dst, q / t as weight from e join (select src, sum(q) as t from e group by src) d on d.src = e.src"),
    ("base", "select id, 0.15::double as fixed, 1.0::double as score from v"), *loop_sql("s", "links", "base", 5)) + " select id, round(score, 6) as score from s5")
def rank_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and parts, weighted by the quantity ordered, both ways."""
    from hotgraph.sources.graphs import PART_OFFSET
    from hotgraph.sources.tables import table

    o, li = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    met = o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("src"), (F.col("l_partkey") + PART_OFFSET).alias("dst")).agg(F.sum("l_quantity").alias("q"))
    both = settle(met.union(met.select(F.col("dst"), F.col("src"), "q")), "weighted")
    return _r(rank_exact(both, iterations=5, weight_col="q", kernel="auto"), "score")


# Hot set --------------------------------------------------------------------------------------------------------------


def _seeds_key(name: str, r: float) -> None:
    @key(name, ctes(*AT, seeds_sql(r)) + " select id, reason from seeds")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        at = point(spark, sf_dir)
        return select_changed(degree_change(at.before, at.now), r)


_seeds_key("seeds_changed", 0.2)
_seeds_key("seeds_changed_fine", 0.05)
_seeds_key("seeds_changed_zero", 0.0)


def _ring_key(n: int) -> None:
    @key(f"ring_hops_{n}", ctes(*AT, seeds_sql(0.2), *ring_sql(n)) + " select id, hop from core where hop > 0")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        at = point(spark, sf_dir)
        return expand_hops(at.now, select_changed(degree_change(at.before, at.now), 0.2), n)


for _n in (0, 1, 2, 4):
    _ring_key(_n)


def _kind_sql(kind: str) -> list[tuple[str, str]]:
    """k0, k1: degrees of another kind before and after; and the seeds by them."""
    ends_of = {"in": "select dst as id from {0}", "total": "select src as id from {0} union all select dst from {0}"}[kind]
    return [
        *((f"k{t}", f"select v.id, count(o.id) as n from v{t} v left join ({ends_of.format(f'e{t}')}) o on o.id = v.id group by v.id") for t in (0, 1)),
        ("seeds", "select k1.id, case when k0.id is null then 'new' else 'changed' end as reason from k1 left join k0 on k0.id = k1.id where k0.id is null or abs(k1.n - k0.n) > 0.2::double * k0.n"),
    ]


def _kind_key(kind: str) -> None:
    @key(f"seeds_changed_{kind}", ctes(*AT, *_kind_sql(kind)) + " select id, reason from seeds")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        at = point(spark, sf_dir)
        return select_changed(degree_change(at.before, at.now, kind), 0.2)


_kind_key("in")
_kind_key("total")


@key("seeds_zero_excluded", ctes(*AT, ("seeds", "select d1.id, case when d0.id is null then 'new' else 'changed' end as reason from d1 left join d0 on d0.id = d1.id where d0.id is null or (abs(d1.n - d0.n) > 0.2::double * d0.n and d0.n > 0)")) + " select id, reason from seeds")
def seeds_zero_excluded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Growth from no edges at all does not make a seed."""
    at = point(spark, sf_dir)
    return select_hot(at.now, at.before, at.scores, P.but(n=0, delta=None, zero_policy="exclude")).select("id", "reason")


_WAYS = {"in": "select dst as src, src as dst from e1", "both": "select src, dst from e1 union select dst, src from e1"}


def _way_key(way: str) -> None:
    ring = [(n, t.replace("join near", "JOIN near").replace("from near", "FROM near").replace(" e1 ", " way ").replace("e1.", "way.")) for n, t in bfs_sql("near", "seeds", 2)]

    @key(f"ring_hops_{way}", ctes(*AT, seeds_sql(0.2), ("way", _WAYS[way]), *ring) + " select id, hop from near where hop > 0")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        at = point(spark, sf_dir)
        return expand_hops(at.now, select_changed(degree_change(at.before, at.now), 0.2), 2, way)


_way_key("in")
_way_key("both")


def _influence(spark: SparkSession, sf_dir: str, mode: str, delta: float, threshold: str = "absolute", max_hops: int | None = None) -> DataFrame:
    at = point(spark, sf_dir)
    core = hot(spark, sf_dir, P.but(delta=None))
    mean = mean_degree(at.now).first()["mean_degree"]
    return _r(expand_by_influence(at.now, core, core, at.scores, delta, mean=mean, mode=mode, threshold=threshold, max_hops=max_hops), "budget")


def _reading_key(name: str, mean: str, known: str, **reading) -> None:  # noqa: ANN003
    """The hot set of select_hot with one reading other than the usual one."""
    parts = [("mean", f"select ({mean}) as m"), ("known", known), *[x for x in candidate_sql(0.1) if x[0] not in ("mean", "known")]]

    @key(name, ctes(*SCORED, seeds_sql(0.2), *ring_sql(1), *parts) + " select id, reason, hop from core union all select id, 'influence', hop from infl")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        at = point(spark, sf_dir)
        ids = at.updates.where("batch = 1").select(F.explode(F.array("src", "dst")).alias("id"))
        older = rank_exact(at.before, iterations=5, kernel="auto")
        return select_hot(at.now, at.before, at.scores, P.but(delta=0.1, **reading), previous_scores=older, touched=ids)


_reading_key(
    "hot_set_touched_mean", "select avg(n) from d1 where id in (select src from adds where batch = 1 union select dst from adds where batch = 1 union select src from del1 union select dst from del1) and id in (" + ends_sql("e1") + ")",
    KNOWN[1][1], mean_degree="touched",
)
_reading_key(
    "hot_set_score_change", KNOWN[0][1][len("select "):].removesuffix(" as m"),
    KNOWN[1][1].replace("coalesce(x.score, 1.0) as s", "coalesce(abs((x.score - o.score) / o.score), 1.0) as s").replace(", mean where", " left join x5 o on o.id = d1.id, mean where"),
    signal="score_change",
)


def _candidate_key(name: str, delta: float) -> None:
    @key(name, ctes(*SCORED, seeds_sql(0.2), *ring_sql(1), *candidate_sql(delta)) + " select id, hop, round(budget, 6) as budget from infl")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _influence(spark, sf_dir, "candidate", delta)


_candidate_key("ring_influence_candidate", 0.5)
_candidate_key("ring_influence_candidate_fine", 0.1)
_candidate_key("ring_influence_candidate_coarse", 1.0)


@key("ring_influence_relative", ctes(*SCORED, seeds_sql(0.2), *ring_sql(1), *[(n, t.replace("coalesce(x.score, 1.0) as s", "1.0::double as s")) for n, t in candidate_sql(0.1)]) + " select id, hop, round(budget, 6) as budget from infl")
def ring_influence_relative(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _influence(spark, sf_dir, "candidate", 0.1, "relative")


def _spread_sql(first: str, step: str, least: str, again: str, hops: int) -> list[tuple[str, str]]:
    """All values that arrive over at most `hops`, as rows (id, hop, b); the largest and the first hop are taken at the end."""
    out = [("w0", first)]
    for h in range(1, hops + 1):
        out.append((f"w{h}", f"select e1.dst as id, {h} as hop, max({step}) as b from w{h - 1} w join e1 on e1.src = w.id join d1 on d1.id = w.id where w.b >= {again} group by e1.dst having max({step}) >= {least}"))
    union = " union all ".join(f"select * from w{h}" for h in range(1, hops + 1))
    return [*out, ("got", f"select id, min(hop) as hop, max(b) as budget from ({union}) group by id")]


@key("ring_influence_anchor", ctes(*SCORED, seeds_sql(0.2), *ring_sql(1), *KNOWN, *_spread_sql(f"select k.id, 0 as hop, {_budget(0.5)} as b from known k join core c on c.id = k.id where deg > 0 and s > 0 and {_budget(0.5)} >= 1", "w.b - 1", "0", "1", 14))
    + " select id, hop, round(budget, 6) as budget from got where id not in (select id from core)")
def ring_influence_anchor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _influence(spark, sf_dir, "anchor", 0.5)


@key("ring_path_product", ctes(*SCORED, seeds_sql(0.2), *ring_sql(1), *KNOWN, *_spread_sql("select k.id, 0 as hop, s as b from known k join core c on c.id = k.id where deg > 0", "w.b / d1.n", "0.1", "0", 16))
    + " select id, round(budget, 6) as contribution from got where id not in (select id from core)")
def ring_path_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _influence(spark, sf_dir, "path_product", 0.1).select("id", F.col("budget").alias("contribution"))


@key("hot_set", ctes(*HOT) + " select id, reason, hop from hot")
def hot_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hot(spark, sf_dir).select("id", "reason", "hop")


@key("hot_set_seeds_only", ctes(*AT, seeds_sql(0.2)) + " select id, reason, 0 as hop from seeds")
def hot_set_seeds_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hot(spark, sf_dir, P.but(n=0, delta=None)).select("id", "reason", "hop")


@key("hot_set_no_influence", ctes(*AT, seeds_sql(0.2), *ring_sql(1)) + " select id, reason, hop from core")
def hot_set_no_influence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hot(spark, sf_dir, P.but(delta=None)).select("id", "reason", "hop")


@key("hot_set_no_ring", ctes(*SCORED, seeds_sql(0.2), *ring_sql(0), *candidate_sql(0.5)) + " select id, reason, hop from core union all select id, 'influence', hop from infl")
def hot_set_no_ring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hot(spark, sf_dir, P.but(n=0)).select("id", "reason", "hop")


# Summary --------------------------------------------------------------------------------------------------------------


@key("summary_inner", ctes(*SUMMARY) + " select src, dst, round(weight, 6) as weight from inner_")
def summary_inner(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(summary(spark, sf_dir).inner.select("src", "dst", "weight"), "weight")


@key("summary_boundary", ctes(*SUMMARY) + " select dst, round(inflow, 6) as inflow, n_edges::bigint as n_edges from cold")
def summary_boundary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(summary(spark, sf_dir).inflow, "inflow")


@key("outside_total", ctes(*SUMMARY) + " select round(coalesce(sum(inflow), 0), 6) as outside_total, coalesce(sum(n_edges), 0)::bigint as boundary_edges from cold")
def outside_total_(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(outside_total(summary(spark, sf_dir)), "outside_total")


@key("summary_ratio", ctes(*SUMMARY) + " select i::bigint as inner_edges, c::bigint as boundary_edges, a::bigint as all_edges, round((i + c)::double / a, 6) as ratio from (select (select count(*) from inner_) as i, (select coalesce(sum(n_edges), 0) from cold) as c, (select count(*) from e1) as a)")
def summary_ratio_(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(summary_ratio(summary(spark, sf_dir), point(spark, sf_dir).now), "ratio")


@key("rank_approximate", ctes(*APPROX) + " select id, round(score, 6) as score, is_hot from approx")
def rank_approximate_(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: exact before, one chunk, hot set, summary, loop over the summary, merge; the loop on joins."""
    at = point(spark, sf_dir)
    built = summary(spark, sf_dir)
    built = Summary(settle(built.hot, "ids"), settle(built.inner, "inner"), settle(built.inflow, "inflow"))
    return _r(rank_approximate(built, at.scores, at.vertices, iterations=ROUNDS), "score")


@key("rank_approx_all_hot", ctes(*AT, ("ybase", "select v1.id, 0.15::double as fixed, 1.0::double as score from v1"), ("ylinks", "select e.src, e.dst, 1.0::double / d1.n as weight from e1 e join d1 on d1.id = e.src"), *loop_sql("y", "ylinks", "ybase", ROUNDS)) + f" select id, round(score, 6) as score from y{ROUNDS}")
def rank_approx_all_hot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every vertex hot and a cold start: the same as the exact ranking."""
    at = point(spark, sf_dir)
    built = build_summary(at.now, at.vertices, at.scores)
    return _r(rank_approximate(built, at.scores, at.vertices, iterations=ROUNDS, warm=False, kernel="auto").select("id", "score"), "score")


@key("rank_approx_empty_hot", ctes(*_CO, *exact_sql("s", "e", "v", ROUNDS)) + f" select id, round(score, 6) as score from s{ROUNDS}")
def rank_approx_empty_hot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No vertex hot: the previous scores."""
    e = graph(spark, sf_dir, "copurchase")
    scores = settle(rank_exact(e, iterations=ROUNDS, kernel="auto"), "scores")
    none = ends(e).limit(0)
    built = build_summary(e, none, scores)
    return _r(rank_approximate(built, scores, ends(e), iterations=ROUNDS, kernel="auto").select("id", "score"), "score")


@key("rank_warm_recompute", ctes(*SCORED, ("zlinks", "select e.src, e.dst, 1.0::double / d1.n as weight from e1 e join d1 on d1.id = e.src"), ("zbase", f"select v1.id, 0.15::double as fixed, coalesce(x.score, 1.0) as score from v1 left join x{ROUNDS} x on x.id = v1.id"), *loop_sql("z", "zlinks", "zbase", 5)) + " select id, round(score, 6) as score from z5")
def rank_warm_recompute(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = point(spark, sf_dir)
    return _r(power_loop(weighted(at.now), at.vertices, iterations=5, start=at.scores, kernel="auto"), "score")


def _chunk_sql(q: int) -> list[tuple[str, str]]:
    """State after chunk q of the stream, r = 0.2, n = 1, no influence ring: E{q}, V{q}, Z{q}."""
    b, taken = q - 1, " union all ".join(f"select src, dst from D{k}" for k in range(1, q)) or "select src, dst from e0 where false"
    return [
        (f"D{q}", f"select src, dst from (select src, dst from e0 union all select src, dst from adds where batch < {q}) where (src, dst) not in (select (src, dst) from ({taken})) order by {key_sql(42000 + q)}, src, dst limit {GONE}"),
        (f"E{q}", f"select src, dst from E{b} where (src, dst) not in (select (src, dst) from D{q}) union select src, dst from adds where batch = {q}"),
        (f"V{q}", f"select id from V{b} union " + ends_sql(f"E{q}")),
        (f"N{q}", f"select v.id, count(e.src) as n from V{q} v left join E{q} e on e.src = v.id group by v.id"),
        (f"K{q}s", f"select a.id from N{q} a left join N{b} b on b.id = a.id where b.id is null or abs(a.n - b.n) > 0.2::double * b.n"),
        (f"K{q}", f"select id from K{q}s union select e.dst from E{q} e join K{q}s s on s.id = e.src"),
        (f"A{q}", f"select e.src, e.dst, n.n as deg, z.score, e.src in (select id from K{q}) as inside from E{q} e join N{q} n on n.id = e.src left join Z{b} z on z.id = e.src where e.dst in (select id from K{q})"),
        (f"L{q}", f"select src, dst, 1.0::double / deg as weight from A{q} where inside"),
        (f"B{q}", f"select k.id, 0.15 + 0.85 * coalesce(c.inflow, 0) as fixed, coalesce(z.score, 1.0) as score from K{q} k left join (select dst, sum(coalesce(score, 0) / deg) as inflow from A{q} where not inside group by dst) c on c.dst = k.id left join Z{b} z on z.id = k.id"),
        *loop_sql(f"P{q}_", f"L{q}", f"B{q}", 5),
        (f"Z{q}", f"select v.id, coalesce(p.score, z.score, 0.15) as score from V{q} v left join P{q}_5 p on p.id = v.id left join Z{b} z on z.id = v.id"),
    ]


@key("replay_final_scores", ctes(*STREAM, ("V0", ends_sql("E0")), ("N0", "select v.id, count(e.src) as n from V0 v left join E0 e on e.src = v.id group by v.id"),
    *exact_sql("q", "E0", "V0", 5), ("Z0", "select id, score from q5"), *_chunk_sql(1), *_chunk_sql(2), *_chunk_sql(3)) + " select id, round(score, 6) as score from Z3")
def replay_final_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three chunks through the serving session, approximate answers throughout."""
    at = point(spark, sf_dir)
    session = QuerySession(at.before, Params(0.2, 1, None, iterations=5), Hooks(policies.always("approximate"))).start()
    for q in (1, 2, 3):
        session.enqueue(at.updates.where(F.col("batch") == q))
        session.query()
    return _r(session.scores, "score")


# Other programs and baselines -----------------------------------------------------------------------------------------


@key("eigen_centrality", ctes(*_CO, ("s0", "select id, 1.0::double as x from v"), *((f"s{k}", f"select v.id, coalesce(g.got, 0) / (max(coalesce(g.got, 0)) over ()) as x from v left join (select e.dst, sum(s.x) as got from e join s{k - 1} s on s.id = e.src group by e.dst) g on g.dst = v.id") for k in range(1, ROUNDS + 1))) + f" select id, round(x, 6) as value from s{ROUNDS}")
def eigen_centrality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(programs.run(programs.eigen_centrality(), graph(spark, sf_dir, "copurchase"), ROUNDS), "value")


_THIRD = "id % 3 = 0"


@key("eigen_summary", ctes(*_CO, ("s0", "select id, 1.0::double as x from v"), *((f"s{k}", f"select v.id, coalesce(g.got, 0) / (max(coalesce(g.got, 0)) over ()) as x from v left join (select e.dst, sum(s.x) as got from e join s{k - 1} s on s.id = e.src group by e.dst) g on g.dst = v.id") for k in range(1, 4)),
    ("hot", f"select id from v where {_THIRD}"), ("cold", f"select e.dst, sum(s.x) as x from e join s3 s on s.id = e.src where e.dst in (select id from hot) and e.src not in (select id from hot) group by e.dst"),
    ("rest", "select sum(s.x) as m from e join s3 s on s.id = e.src where e.dst = (select id from s3 where id not in (select id from hot) order by x desc, id limit 1)"), ("t0", "select id, x from s3 where id in (select id from hot)"),
    *((f"t{k}", f"select h.id, (coalesce(g.got, 0) + coalesce(c.x, 0)) / greatest(coalesce(m, 0), max(coalesce(g.got, 0) + coalesce(c.x, 0)) over ()) as x from hot h left join (select e.dst, sum(t.x) as got from e join t{k - 1} t on t.id = e.src group by e.dst) g on g.dst = h.id left join cold c on c.dst = h.id, rest") for k in range(1, 6)))
    + " select id, round(x, 6) as value, true as is_hot from t5 union all select id, round(x, 6), false from s3 where id not in (select id from hot)")
def eigen_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Another program through the summary: a third of the vertices is hot, the rest keeps the values of three exact rounds."""
    e = graph(spark, sf_dir, "copurchase")
    old = settle(programs.run(programs.eigen_centrality(), e, 3), "old")
    return _r(programs.run_summary(programs.eigen_centrality(), e, ends(e).where(_THIRD), old, 5), "value")


@key("page_rank_summary", ctes(*APPROX) + " select id, round(score, 6) as value, is_hot from approx")
def page_rank_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ranking as a program through the summary: the same as the approximate ranking."""
    at = point(spark, sf_dir)
    old = at.scores.withColumnRenamed("score", "value")
    found = programs.run_summary(programs.page_rank(), at.now, hot(spark, sf_dir), old, ROUNDS)
    whole = at.vertices.join(found, "id", "left").select("id", F.coalesce("value", F.lit(0.15)).alias("value"), F.coalesce("is_hot", F.lit(False)).alias("is_hot"))
    return _r(whole, "value")


@key("page_rank_program", ctes(*_CO, *exact_sql("s", "e", "v", 5)) + " select id, round(score, 6) as value from s5")
def page_rank_program(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(programs.run(programs.page_rank(), graph(spark, sf_dir, "copurchase"), 5, style="gather"), "value")


@key("sssp_hops", ctes(("e1", GRAPH_SQL["social_urgent"]), ("one", "select min(id) as id from (" + ends_sql("e1") + ")"), *bfs_sql("far", "one", 40)) + " select id, hop from far")
def sssp_hops(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = graph(spark, sf_dir, "social_urgent")
    source = ends(e).agg(F.min("id")).first()[0]
    found = programs.run(programs.shortest_hops(source if source is not None else -1), e, None)
    return found.where("value is not null").select("id", F.col("value").alias("hop"))


@key("label_communities", ctes(("e", GRAPH_SQL["social_urgent"]), ("v", ends_sql("e")), ("l0", "select id, id as value from v"),
    *((f"l{k}", f"select v.id, coalesce(w.value, o.value) as value from v join l{k - 1} o on o.id = v.id left join (select dst, value from (select dst, value, row_number() over (partition by dst order by n desc, value) as k from (select e.dst, l.value, count(*) as n from e join l{k - 1} l on l.id = e.src group by 1, 2)) where k = 1) w on w.dst = v.id") for k in range(1, 6))) + " select id, value from l5")
def label_communities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return programs.label_communities(graph(spark, sf_dir, "social_urgent"), 5)


_SHARE = "('0x' || substr(md5({0}), 1, 12))::bigint / 281474976710656.0"


@key("baseline_sample", ctes(("g", GRAPH_SQL["copurchase"]), ("v", ends_sql("g")), ("e", f"select src, dst from g where {_SHARE.format(key_sql(42)[4:-1])} < 0.5"), *exact_sql("s", "e", "v", 5)) + " select id, round(score, 6) as score from s5")
def baseline_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(baselines.baseline_sample(graph(spark, sf_dir, "copurchase"), 0.5, iterations=5, kernel="auto"), "score")


@key("baseline_drop_tasks", ctes(("g", GRAPH_SQL["copurchase"]), ("v", ends_sql("g")), ("e", "select src, dst from g where floor(" + _SHARE.format("src::varchar || '-42'") + " * 8) < 6"), *exact_sql("s", "e", "v", 5)) + " select id, round(score, 6) as score from s5")
def baseline_drop_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(baselines.baseline_drop_tasks(graph(spark, sf_dir, "copurchase"), 8, 6, iterations=5, kernel="auto"), "score")


@key("baseline_shed", ctes(*STREAM) + " select src, dst from adds where " + _SHARE.format("src::varchar || '-' || dst::varchar || '-e+-42'") + " < 0.5")
def baseline_shed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.baseline_shed(point(spark, sf_dir).updates.where("op = 'e+'"), 0.5).select("src", "dst")


@key("baseline_reuse", ctes(*SCORED) + f" select id, round(score, 6) as score from x{ROUNDS}")
def baseline_reuse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The previous answer, whatever has changed since."""
    at = point(spark, sf_dir)
    session = QuerySession(at.before, P, Hooks(policies.always("reuse"))).start(at.scores)
    session.enqueue(at.updates.where("batch = 1"))
    return _r(session.query(), "score")
