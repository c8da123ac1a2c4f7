"""Experiments: replays of a fixed stream by a strategy and a parameter set, grids of sets, and their reports."""

from __future__ import annotations

import os
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.operators import measures
from hotgraph.operators.iterate import fits, rank_exact
from hotgraph.operators.ranks import global_rank, list_length, top
from hotgraph.operators.updates import make_stream
from hotgraph.plans import policies
from hotgraph.plans.experiment import FULL_EVERY, REPLAY_LINKS, experiment
from hotgraph.plans.session import RUN_LOG, Hooks, QuerySession
from hotgraph.schema import Params
from hotgraph.sources.graphs import BUILDERS, symmetric
from hotgraph.storage import counted, settle

#: The parameter sets of the two grids, (r, n, delta).
ACCURACY_SETS = [(0.05, 2, 0.5), (0.05, 2, 1.0), (0.05, 6, 0.5), (0.05, 6, 1.0)]
SPEED_SETS = [(0.20, 0, 0.5), (0.20, 0, 1.0), (0.20, 1, 0.5), (0.20, 1, 1.0), (0.20, 4, 1.0)]
#: For dense graphs, where larger r leaves no seeds.
DENSE_SETS = [(0.01, 0, 0.5), (0.02, 0, 0.5)]
#: Share of all edges that a stream adds over all its queries.
STREAM_SHARE = {"web": 0.002, "social": 0.025, "copurchase": 0.008}
GRAPHS = {"web": "web_circulating", "social": "social_urgent", "copurchase": "copurchase"}

def grid(name: str) -> list[Params]:
    if name == "all":
        return [*grid("accuracy"), *grid("speed")]
    if name == "influence":  # all readings of the influence ring
        return [
            Params(0.2, 1, d, mode=m, threshold=t)
            for d in (0.1, 0.5, 1.0) for m in ("candidate", "anchor", "path_product") for t in ("absolute", "relative")
        ]
    sets = {"accuracy": ACCURACY_SETS, "speed": SPEED_SETS, "dense": DENSE_SETS}[name]
    return [Params(*s) for s in sets]


@dataclass(frozen=True)
class Workload:
    """A graph with a fixed stream over it."""

    name: str
    initial: DataFrame
    updates: DataFrame
    queries: int


def edges_of(spark: SparkSession, sf_dir: str, name: str, symmetric_edges: bool = False) -> DataFrame:
    edges = BUILDERS[GRAPHS.get(name, name)](spark, sf_dir)
    return settle(symmetric(edges) if symmetric_edges else edges, "graph")


def workload(
    spark: SparkSession, sf_dir: str, name: str, queries: int = 50, *, chunk: int | None = None, deletion_ratio: float = 0.2,
    order: str = "shuffled", symmetric_edges: bool = False, seed: int = 42, edges: DataFrame | None = None,
) -> Workload:
    """name is web, social or copurchase; chunk is the number of additions for each query, else the usual share of edges.
    edges: those of edges_of(), where they are made already.
    """
    edges = edges_of(spark, sf_dir, name, symmetric_edges) if edges is None else edges
    size = chunk * queries if chunk else max(queries, round(counted(edges) * STREAM_SHARE.get(name, 0.01)))
    initial, updates = make_stream(edges, size, queries, deletion_ratio, seed, order)
    return Workload(name, initial, settle(updates, "updates"), queries)


def replay(
    work: Workload, params: Params = Params(), strategy: str = "approximate", *, policy: policies.Policy | None = None, kernel: str = "auto",
    queries: int | None = None, first: DataFrame | None = None, each: Callable[[int, QuerySession], None] | None = None,
    local_links: int | None = None,
) -> tuple[QuerySession, list[DataFrame]]:
    """The session after the stream, and the answers, the first exact one included."""
    hooks = Hooks(policy or policies.always(strategy))
    session = QuerySession(work.initial, params, hooks, name=work.name, kernel=kernel, local_links=local_links, distinct=True).start(first)
    answers = [session.scores]
    for q in range(1, (queries or work.queries) + 1):
        session.enqueue(work.updates.where(F.col("batch") == q))
        answers.append(session.query())
        if each is not None:
            each(q, session)
    session.stop()
    return session, answers


def compare(
    exact: list[DataFrame], approximate: list[DataFrame], session: QuerySession, p: float = 0.98, *, second_p: bool = True
) -> DataFrame:
    """(set_id, query, metric, value) of the answers against the exact ones at the same queries."""
    spark, label, out = session.spark, session.params.label, []
    for q, (a, b) in enumerate(zip(approximate[1:], exact[1:], strict=False), 1):
        k = list_length(b.count())
        ta, tb = settle(top(a, k), "top"), settle(top(b, k), "top")
        found = [("rbo", measures.rbo(ta, tb, k, p).select("rbo")), ("overlap", measures.overlap_at(ta, tb, k).select("overlap"))]
        if second_p and k > 1:
            found.append(("rbo_wide", measures.rbo(ta, tb, k, 1 - 1 / k).select("rbo")))
        if q % FULL_EVERY == 0:
            n = b.count()
            full = measures.rbo(global_rank(a), global_rank(b), min(n, measures.depth_needed(p, n)), p)
            found.append(("rbo_full", full.select("rbo")))
        found.append(("score_l1", measures.score_error(a, b).select("l1")))
        out += [(label, q, metric, float(df.first()[0])) for metric, df in found]
    for row in session.rows:
        share = (row["inner_edges"] + row["boundary_edges"]) / max(1, row["n_edges"])
        out += [(label, row["query"], "edge_ratio", share), (label, row["query"], "seconds", sum(row["phases"].values()))]
    return spark.createDataFrame(out, "set_id string, query int, metric string, value double")


def with_speedup(runs: DataFrame, exact: QuerySession, approximate: QuerySession) -> DataFrame:
    """runs with total and compute speedups of each query."""
    label = F.lit(approximate.params.label).alias("set_id")
    for kind in ("total", "compute"):
        s = measures.speedup(exact.run_log(), approximate.run_log(), kind)
        runs = runs.unionByName(s.select(label, "query", F.lit(f"speedup_{kind}").alias("metric"), F.col("speedup").alias("value")))
    return runs


def report(runs: DataFrame, path: str) -> None:
    """The long table (set_id, query, metric, value) as Parquet and CSV."""
    runs.write.mode("overwrite").parquet(f"{path}/parquet")
    runs.write.mode("overwrite").option("header", True).csv(f"{path}/csv")


def ran(work: Workload, sets: list[Params], kernel: str = "auto") -> DataFrame:
    """(graph, set_id, query, metric, value) of all sets over one stream, each against exact answers to the same queries.

    A graph that fits one task is replayed there, set by set, against exact answers made once; a larger one through the serving session.
    """
    if kernel != "distributed" and fits(REPLAY_LINKS, work.initial, work.updates):
        return experiment(work.initial, work.updates, sets, work.queries, work.name)
    exact_session, exact = replay(work, sets[0], policies.RECOMPUTE, kernel=kernel)
    out = None
    for p in sets:
        session, answers = replay(work, p, policies.APPROXIMATE, kernel=kernel, first=exact[0])
        runs = with_speedup(compare(exact, answers, session), exact_session, session)
        runs = runs.select(F.lit(work.name).alias("graph"), "set_id", "query", "metric", "value")
        out = runs if out is None else out.unionByName(runs)
    return out


def summary_of(runs: DataFrame) -> DataFrame:
    """(graph, set_id, metric, queries, mean, first, last): each measure over the queries of a run."""
    return runs.groupBy("graph", "set_id", "metric").agg(
        F.count("*").alias("queries"), F.avg("value").alias("mean"), F.min_by("value", "query").alias("first"), F.max_by("value", "query").alias("last")
    )


def scaling(work: Workload, parts: list[int], params: Params = Params(0.05, 2, 1.0)) -> DataFrame:
    """(parts, strategy, phase, seconds): both strategies with the shuffles of the loops in so many partitions, which
    bounds the tasks that run at once. The setting is put back. The answer before the stream is in no phase, so the first
    session's serves all.
    """
    spark, name, rows, first = work.initial.sparkSession, "spark.sql.shuffle.partitions", [], None
    usual = spark.conf.get(name)
    try:
        for n in parts:
            spark.conf.set(name, n)
            for strategy in (policies.RECOMPUTE, policies.APPROXIMATE):
                session, answers = replay(work, params, strategy, kernel="distributed", first=first)
                first = answers[0]
                for phase in ("ingest", "construct", "compute"):
                    rows.append((n, strategy, phase, sum(r["phases"].get(phase, 0.0) for r in session.rows)))
    finally:
        spark.conf.set(name, usual)
    return spark.createDataFrame(rows, "parts int, strategy string, phase string, seconds double")


def staleness_curve(work: Workload, params: Params = Params(), every: int = 1, kernel: str = "auto", p: float = 0.98) -> DataFrame:
    """(query, pending, rbo): the first answer, reused, against exact ones as updates pile up."""
    _, exact = replay(work, params, policies.RECOMPUTE, kernel=kernel)
    counts = {r.batch: r["count"] for r in work.updates.groupBy("batch").count().collect()}
    out, pending = [], 0
    for q in range(1, work.queries + 1):
        pending += counts.get(q, 0)
        if q % every == 0:
            k = list_length(exact[q].count())
            out.append((q, pending, measures.rbo(top(exact[0], k), top(exact[q], k), k, p).first()["rbo"]))
    return work.initial.sparkSession.createDataFrame(out, "query int, pending bigint, rbo double")


def growth_report(work: Workload, params: Params = Params(), kernel: str = "auto") -> DataFrame:
    """(query, reason, n): vertices by the reason they became hot, at each query."""
    out: list[tuple] = []

    def note(q: int, session: QuerySession) -> None:
        out.extend((q, r.reason, r["count"]) for r in session.hot.groupBy("reason").count().collect())

    replay(work, params, policies.APPROXIMATE, kernel=kernel, each=note)
    return work.initial.sparkSession.createDataFrame(out, "query int, reason string, n bigint")


def scaling_run(sf_dir: str, cores: list[int], name: str = "copurchase", queries: int = 3, params: Params = Params(0.05, 2, 1.0)) -> list[dict]:
    """Seconds by phase of both strategies at several core counts, each in a process of its own (a session's core count is fixed)."""
    import json
    import subprocess
    import sys

    code = (
        "import sys, json\nfrom pyspark.sql import SparkSession\nfrom hotgraph.plans.workloads import *\n"
        "cores, sf, name, q, r, n, d = sys.argv[1:]\n"
        "spark = SparkSession.builder.master(f'local[{cores}]').config('spark.ui.enabled', 'false')"
        ".config('spark.sql.shuffle.partitions', max(4, int(cores))).getOrCreate()\n"
        "w = workload(spark, sf, name, int(q)); p = Params(float(r), int(n), float(d)); out = []\n"
        "for s in ('recompute', 'approximate'):\n"
        "    session, _ = replay(w, p, s, kernel='distributed')\n"
        "    for row in session.rows: out.append(dict(cores=int(cores), strategy=s, query=row['query'], **row['phases']))\n"
        "print('ROWS' + json.dumps(out))\n"
    )
    rows = []
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    for c in cores:
        args = [sys.executable, "-c", code, str(c), sf_dir, name, str(queries), str(params.r), str(params.n), str(params.delta)]
        env = os.environ | {"PYTHONPATH": os.pathsep.join([root, os.environ.get("PYTHONPATH", "")])}
        done = subprocess.run(args, capture_output=True, text=True, cwd=root, env=env, check=True)
        rows += json.loads(done.stdout.rpartition("ROWS")[2])
    return rows


def timed(make: Callable[[], DataFrame]) -> tuple[float, DataFrame]:
    """Seconds until the frame is written, and the written frame."""
    began = time.perf_counter()
    done = settle(make(), "timed")
    return time.perf_counter() - began, done


__all__ = [
    "FULL_EVERY", "RUN_LOG", "Params", "Workload", "compare", "edges_of", "grid", "growth_report", "ran", "rank_exact", "replay", "report", "scaling",
    "scaling_run", "staleness_curve", "summary_of", "timed", "with_speedup", "workload",
]
