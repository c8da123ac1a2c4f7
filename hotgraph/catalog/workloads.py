"""Experiments as queries. Each replays the workload's own stream, QUERIES queries of it and 30 rounds for each, over whole
grids, and reports every measure. Those with measured times have no oracle; the chain at the end has one in SQL.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.catalog.base import GRAPH_SQL, ctes, ends_sql, exact_sql, held, key, loop_sql, once
from hotgraph.catalog.core import GONE, STREAM, key_sql, point
from hotgraph.catalog.graphs import graph
from hotgraph.operators import measures
from hotgraph.plans import policies
from hotgraph.plans.experiment import experiment
from hotgraph.plans.session import Hooks, QuerySession
from hotgraph.plans.workloads import Workload, edges_of, grid, growth_report, ran, replay, report, scaling, staleness_curve, summary_of, workload
from hotgraph.schema import Params
from hotgraph.sources.tables import scratch
from hotgraph.storage import settle

QUERIES = 50
#: Streams and replays that are under way at a time: small graphs fill what the largest leaves idle; tasks are as many as before.
AT_ONCE = 3


def _work(spark: SparkSession, sf_dir: str, name: str, queries: int = QUERIES, **more) -> Workload:  # noqa: ANN003
    make = lambda: workload(spark, sf_dir, name, queries, edges=_edges(spark, sf_dir, name, more.get("symmetric_edges", False)), **more)
    return once(spark, "work", sf_dir, name, queries, *sorted(more.items()), make=make)


def _edges(spark: SparkSession, sf_dir: str, name: str, both_ways: bool = False) -> DataFrame:
    return once(spark, "edges", sf_dir, name, both_ways, make=lambda: edges_of(spark, sf_dir, name, both_ways))


def _together(makes: list[Callable[[], DataFrame]]) -> DataFrame:
    """Union of what is made, AT_ONCE at a time."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        first, *rest = pool.map(lambda make: make(), makes)
    for more in rest:
        first = first.unionByName(more)
    return first


def _runs(spark: SparkSession, sf_dir: str, name: str, sets: str = "all", label: str | None = None, **more) -> DataFrame:  # noqa: ANN003
    """(graph, set_id, query, metric, value) of a grid's sets, made once a session."""

    def make() -> DataFrame:
        if sets in ("accuracy", "speed") and (every := held(spark, "runs", sf_dir, name, "all", label, *sorted(more.items()))) is not None:
            return every.where(F.col("set_id").isin([p.label for p in grid(sets)]))
        found = ran(_work(spark, sf_dir, name, **more), grid(sets))
        return settle(found.withColumn("graph", F.lit(label)) if label else found, "runs")

    return once(spark, "runs", sf_dir, name, sets, label, *sorted(more.items()), make=make)


def _graph_key(name: str) -> None:
    @key(f"workload_{name}")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _runs(spark, sf_dir, name)


for _name in ("web", "social", "copurchase"):
    _graph_key(_name)


@key("workload_social_symmetric")
def workload_social_symmetric(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The social graph with every edge both ways."""
    return _runs(spark, sf_dir, "social", label="social_symmetric", symmetric_edges=True)


def _all_graphs(spark: SparkSession, sf_dir: str, sets: str) -> DataFrame:
    """Runs of the sets on all three graphs, the largest first."""
    return _together([lambda g=g: _runs(spark, sf_dir, g, sets) for g in ("copurchase", "social", "web")])


def _grid_key(name: str) -> None:
    @key(f"workload_{name}_grid")
    def _(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Means over the queries of the grid's sets on all three graphs."""
        return summary_of(_all_graphs(spark, sf_dir, name))


_grid_key("accuracy")
_grid_key("speed")


@key("workload_influence")
def workload_influence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All readings of the influence ring, 18 sets, on one stream."""
    return summary_of(_runs(spark, sf_dir, "social", "influence"))


@key("workload_deletions")
def workload_deletions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same additions with and without deletions, all sets, on the social and the copurchase graph."""
    sides = []
    for g in ("copurchase", "social"):
        _edges(spark, sf_dir, g)  # both sides start from them
        sides += [lambda g=g, label=label, ratio=ratio: _runs(spark, sf_dir, g, label=f"{g}_{label}", deletion_ratio=ratio) for label, ratio in (("with", 0.2), ("without", 0.0))]
    return summary_of(_together(sides))


@key("workload_order")
def workload_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same additions in shuffled order and clustered by source, the same sets on both."""
    _edges(spark, sf_dir, "copurchase")  # both sides start from them
    side = lambda o: lambda: _runs(spark, sf_dir, "copurchase", label=f"copurchase_{o}", order=o)
    return summary_of(_together([side("shuffled"), side("incidence")]))


@key("workload_small_chunks")
def workload_small_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One addition before each of many queries, in place of the usual chunk: the summary is nearly empty throughout."""
    return summary_of(ran(_work(spark, sf_dir, "copurchase", 100, chunk=1), [Params(0.2, 0, 0.5), Params(0.05, 2, 1.0)]))


@key("workload_distributed")
def workload_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The serving session on both sides, every loop and hot set by joins: the way of graphs that do not fit a task."""
    return ran(_work(spark, sf_dir, "social", 2), [Params(0.2, 1, 0.5, iterations=10)], kernel="distributed")


@key("workload_scaling")
def workload_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds by phase of both strategies with 2, 4 and 8 tasks at a time."""
    return scaling(_work(spark, sf_dir, "copurchase", 1), [2, 4, 8], Params(0.05, 2, 1.0, iterations=5))


@key("experiment_report")
def experiment_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The long table of all graphs and sets, written as Parquet and CSV and read back from the latter."""
    every, path = _all_graphs(spark, sf_dir, "all"), scratch(spark, "report")
    report(every, path)
    return spark.read.option("header", True).schema(every.schema).csv(f"{path}/csv")


@key("best_worst_measured")
def best_worst_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three best and three worst sets of each headline measure, from the measured runs of the social graph."""
    runs = _runs(spark, sf_dir, "social").where("metric in ('rbo', 'rbo_wide', 'speedup_total', 'speedup_compute', 'edge_ratio')")
    return measures.best_worst(runs)


@key("series_measured")
def series_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measures of the social graph by query, with the overlap of 1 before the first."""
    return measures.series(_runs(spark, sf_dir, "social").where("metric in ('rbo', 'speedup_total', 'edge_ratio')"))


@key("workload_growth")
def workload_growth(spark: SparkSession, sf_dir: str) -> DataFrame:
    return growth_report(_work(spark, sf_dir, "social", 10), Params(0.2, 1, 0.5))


@key("workload_staleness")
def workload_staleness(spark: SparkSession, sf_dir: str) -> DataFrame:
    return staleness_curve(_work(spark, sf_dir, "social", 10), Params())


# The measures that times do not enter, in SQL --------------------------------------------------------------------------

CHAIN_SETS = [Params(0.2, 0, 0.5), Params(0.2, 1, 0.5), Params(0.05, 2, 1.0), Params(0.05, 6, 0.5)]
CHAIN_ROUNDS, CHAIN_QUERIES = 5, 3


def _hops_sql(name: str, edges: str, start: str, hops: int) -> list[tuple[str, str]]:
    out = [(f"{name}0", f"select distinct id, 0 as hop from {start}")]
    for h in range(1, hops + 1):
        out.append((f"{name}{h}", f"select id, hop from {name}{h - 1} union all select distinct e.dst, {h} from {edges} e join {name}{h - 1} f on f.id = e.src and f.hop = {h - 1} where e.dst not in (select id from {name}{h - 1})"))
    return out


def _graph_sql(q: int) -> list[tuple[str, str]]:
    """D, E, V, N: deletions, edges, vertices and out-degrees after chunk q; Y{q}_5: the exact scores."""
    b, taken = q - 1, " union all ".join(f"select src, dst from D{k}" for k in range(1, q)) or "select src, dst from e0 where false"
    return [
        (f"D{q}", f"select src, dst from (select src, dst from e0 union all select src, dst from adds where batch < {q}) where (src, dst) not in (select (src, dst) from ({taken})) order by {key_sql(42000 + q)}, src, dst limit {GONE}"),
        (f"E{q}", f"select src, dst from E{b} where (src, dst) not in (select (src, dst) from D{q}) union select src, dst from adds where batch = {q}"),
        (f"V{q}", f"select id from V{b} union " + ends_sql(f"E{q}")),
        (f"N{q}", f"select v.id, count(e.src) as n from V{q} v left join E{q} e on e.src = v.id group by v.id"),
        (f"M{q}", f"select (select count(*) from E{q})::double / (select count(*) from ({ends_sql(f'E{q}')})) as m"),
        *exact_sql(f"Y{q}_", f"E{q}", f"V{q}", CHAIN_ROUNDS),
    ]


def _set_sql(t: str, p: Params, q: int) -> list[tuple[str, str]]:
    """K, A, Z of set t after chunk q: hot set, edges into it, scores."""
    b, score = q - 1, f"Z{t}_{q - 1}"
    infl = (
        f"select f.id from {t}far{q}_8 f join N{q} d on d.id = f.id left join {score} z on z.id = f.id, M{q} where f.hop > 0 and d.n > 0 "
        f"and f.id in ({ends_sql(f'E{q}')}) and coalesce(z.score, 1.0) >= {p.delta} * d.n * pow(m, f.hop - 1)"
    )
    return [
        (f"{t}S{q}", f"select a.id from N{q} a left join N{b} b on b.id = a.id where b.id is null or abs(a.n - b.n) > {p.r}::double * b.n"),
        *_hops_sql(f"{t}near{q}_", f"E{q}", f"{t}S{q}", p.n), *_hops_sql(f"{t}far{q}_", f"E{q}", f"{t}near{q}_{p.n}", 8),
        (f"K{t}_{q}", f"select id from {t}near{q}_{p.n} union {infl}"),
        (f"A{t}_{q}", f"select e.src, e.dst, n.n as deg, z.score, e.src in (select id from K{t}_{q}) as inside from E{q} e join N{q} n on n.id = e.src left join {score} z on z.id = e.src where e.dst in (select id from K{t}_{q})"),
        (f"L{t}_{q}", f"select src, dst, 1.0::double / deg as weight from A{t}_{q} where inside"),
        (f"B{t}_{q}", f"select k.id, 0.15 + 0.85 * coalesce(c.inflow, 0) as fixed, coalesce(z.score, 1.0) as score from K{t}_{q} k left join (select dst, sum(coalesce(score, 0) / deg) as inflow from A{t}_{q} where not inside group by dst) c on c.dst = k.id left join {score} z on z.id = k.id"),
        *loop_sql(f"P{t}_{q}_", f"L{t}_{q}", f"B{t}_{q}", CHAIN_ROUNDS),
        (f"Z{t}_{q}", f"select v.id, coalesce(p.score, z.score, 0.15) as score from V{q} v left join P{t}_{q}_{CHAIN_ROUNDS} p on p.id = v.id left join {score} z on z.id = v.id"),
    ]


CHAIN = [
    *STREAM, ("V0", ends_sql("e0")), ("N0", "select v.id, count(e.src) as n from V0 v left join e0 e on e.src = v.id group by v.id"),
    *exact_sql("Y0_", "e0", "V0", CHAIN_ROUNDS), *(part for q in range(1, CHAIN_QUERIES + 1) for part in _graph_sql(q)),
]
CHAIN_TAGS = {f"c{t}": p for t, p in enumerate(CHAIN_SETS)}
for _t, _p in CHAIN_TAGS.items():
    CHAIN.append((f"Z{_t}_0", f"select id, score from Y0_{CHAIN_ROUNDS}"))
    for _q in range(1, CHAIN_QUERIES + 1):
        CHAIN += _set_sql(_t, _p, _q)
_EACH = [(t, p, q) for t, p in CHAIN_TAGS.items() for q in range(1, CHAIN_QUERIES + 1)]


def _chain(spark: SparkSession, sf_dir: str, final: bool = False) -> DataFrame:
    at = point(spark, sf_dir)
    sets = [p.but(iterations=CHAIN_ROUNDS) for p in CHAIN_SETS]
    make = lambda: experiment(at.before, at.updates.where(F.col("batch") <= CHAIN_QUERIES), sets, CHAIN_QUERIES, "social", final)
    return once(spark, "chain", sf_dir, final, make=make)


@key("experiment_work", ctes(*CHAIN) + " union all ".join(
    f" select '{p.label}' as set_id, {q}::int as query, (select count(*) from K{t}_{q})::bigint as n_hot, (select count(*) from L{t}_{q})::bigint as inner_edges, "
    f"(select count(*) from A{t}_{q} where not inside)::bigint as boundary_edges, (select count(*) from E{q})::bigint as n_edges" for t, p, q in _EACH))
def experiment_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of hot set and summary, set by set and query by query."""
    runs = _chain(spark, sf_dir)
    one = lambda m: F.max(F.when(F.col("metric") == m, F.col("value"))).cast("bigint").alias(m)
    return runs.groupBy("set_id", "query").agg(*map(one, ("n_hot", "inner_edges", "boundary_edges", "n_edges")))


@key("experiment_scores", ctes(*CHAIN) + " union all ".join(
    f" select '{p.label}' as set_id, id, round(score, 6) as score from Z{t}_{CHAIN_QUERIES}" for t, p in CHAIN_TAGS.items()))
def experiment_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Approximate scores after the last query of each set's replay."""
    return _chain(spark, sf_dir, final=True).select("set_id", "id", F.round("score", 6).alias("score"))


def _lists_sql() -> list[tuple[str, str]]:
    out = []
    for q in range(1, CHAIN_QUERIES + 1):
        out.append((f"LE{q}", f"select id, row_number() over (order by round(score, 9) desc, id) as rank from Y{q}_{CHAIN_ROUNDS}"))
        out.append((f"KK{q}", f"select least(count(*), greatest(10, ceil(0.1 * count(*))))::bigint as k from V{q}"))
        out.append((f"W{q}", f"select d as m, sum(pow(0.98::double, d - 1) / d) over (order by d desc) as w from (select unnest(range(1, (select k + 1 from KK{q}))) as d)"))
    for t, _, q in _EACH:
        out.append((f"LA{t}_{q}", f"select id, row_number() over (order by round(score, 9) desc, id) as rank from Z{t}_{q}"))
        out.append((f"MM{t}_{q}", f"select greatest(a.rank, b.rank) as m from LA{t}_{q} a join LE{q} b on a.id = b.id, KK{q} where a.rank <= k and b.rank <= k"))
    return out


@key("experiment_rbo", ctes(*CHAIN, *_lists_sql()) + " union all ".join(
    f" select '{p.label}' as set_id, {q}::int as query, round(0.02::double * (select coalesce(sum(w), 0) from MM{t}_{q} join W{q} using (m)) + pow(0.98::double, k) / k * (select count(*) from MM{t}_{q}), 6) as rbo, "
    f"round((select count(*) from MM{t}_{q})::double / k, 6) as overlap from KK{q}" for t, p, q in _EACH))
def experiment_rbo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of each set's answers, query by query."""
    runs = _chain(spark, sf_dir)
    one = lambda m: F.round(F.max(F.when(F.col("metric") == m, F.col("value"))), 6).alias(m)
    return runs.groupBy("set_id", "query").agg(one("rbo"), one("overlap"))


@key("workload_policies")
def workload_policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which strategy each policy takes, query by query, on one stream."""
    work = _work(spark, sf_dir, "social", 3, chunk=11)
    rows = []
    for name, policy in {"periodic": policies.periodic(2), "by_change": policies.by_change(0.001, 0.5), "latency": policies.by_tier()}.items():
        session, _ = replay(work, Params(0.2, 0, None, iterations=5), policy=policy)
        rows += [(name, r["query"], r["strategy"]) for r in session.rows]
    return spark.createDataFrame(rows, "policy string, query int, strategy string")


_GRIDS = [(g, i, float(p.r), p.n, float(p.delta)) for g in ("accuracy", "speed", "dense") for i, p in enumerate(grid(g))]
_GRIDS_SQL = ", ".join(f"('{g}', {i}::int, {r}::double, {n}::int, {d}::double)" for g, i, r, n, d in _GRIDS)


@key("parameter_grids", ctes(("e", GRAPH_SQL["copurchase"]), ("d", "select src, count(*) as n from e group by src")) + f" select grid, place, r, n, delta, (select count(*) from d where 1.0::double > t.r * d.n)::bigint as n_moved from (values {_GRIDS_SQL}) t(grid, place, r, n, delta)")
def parameter_grids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sets of each grid, and how many sources of the copurchase graph a single added edge makes hot by their r."""
    sets = F.broadcast(spark.createDataFrame(_GRIDS, "grid string, place int, r double, n int, delta double"))  # a few sets
    counts = graph(spark, sf_dir, "copurchase").groupBy("src").agg(F.count("*").alias("deg")).groupBy("deg").agg(F.count("*").alias("sources"))
    moved = F.coalesce(F.sum(F.when(F.lit(1.0) > F.col("r") * F.col("deg"), F.col("sources"))), F.lit(0)).cast("bigint")
    return counts.crossJoin(sets).groupBy("grid", "place", "r", "n", "delta").agg(moved.alias("n_moved"))


@key("serving_log")
def serving_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Run log of a session with all three strategies."""
    work = _work(spark, sf_dir, "social", 3, chunk=11)
    turn = {1: "approximate", 2: "reuse", 3: "recompute"}
    session = QuerySession(work.initial, Params(iterations=5), Hooks(lambda p: turn[p.query]), name="social").start()
    for q in (1, 2, 3):
        session.enqueue(work.updates.where(f"batch = {q}"))
        session.query()
    return session.run_log()
