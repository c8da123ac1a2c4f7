"""The experiment's task against the serving session, hubs, programs through the summary, chains of rows, and storage."""

import os

import pytest
from pyspark.sql import functions as F

from hotgraph import storage
from hotgraph.operators import measures, programs
from hotgraph.operators.iterate import power_loop, rank_exact, weighted
from hotgraph.plans import policies
from hotgraph.plans.experiment import experiment
from hotgraph.plans.session import QuerySession
from hotgraph.plans.workloads import ran, replay, workload
from hotgraph.schema import Params
from hotgraph.sources.graphs import ends, with_next
from hotgraph.sources.tables import scratch
from hotgraph.streaming.serve import EventChain
from tests.test_method import as_dict, graph, near, random_edges

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("more", [{}, {"n": 2, "delta": 0.1, "mode": "path_product"}, {"signal": "score_change", "delta": 0.2, "degree": "total"}, {"mean_degree": "touched", "delta": 0.2}])
def test_task_and_session_agree(spark, more):
    work = workload(spark, SF, "social", 3, chunk=6, deletion_ratio=0.34)
    p = Params(**{"r": 0.2, "n": 1, "delta": 0.5, "iterations": 6, **more})
    session, _ = replay(work, p, policies.APPROXIMATE, kernel="local")
    runs = {(r.query, r.metric): r.value for r in experiment(work.initial, work.updates, [p], 3).collect()}
    for row in session.rows:
        for name in ("n_hot", "inner_edges", "boundary_edges", "n_edges"):
            assert runs[row["query"], name] == row[name], (name, row["query"])
    final = experiment(work.initial, work.updates, [p], 3, final=True).select("id", "score")
    near(as_dict(final), as_dict(session.scores))


def test_ran_has_the_same_measures_either_way(spark):
    work = workload(spark, SF, "social", 2, chunk=5)
    p = Params(0.2, 1, 0.5, iterations=6)
    a, b = ({(r.query, r.metric): r.value for r in ran(work, [p], kernel).collect()} for kernel in ("auto", "distributed"))
    for q in (1, 2):
        for name in ("rbo", "rbo_wide", "overlap", "edge_ratio", "score_l1"):
            assert a[q, name] == pytest.approx(b[q, name], abs=1e-6), name


def test_a_hub_with_half_of_all_links(spark):
    edges = {(0, k) for k in range(1, 120)} | {(k, (k * 7) % 120) for k in range(1, 120) if k != (k * 7) % 120} | {(5, 0)}
    e = graph(spark, edges)
    near(as_dict(power_loop(weighted(e), ends(e), iterations=6, hub_links=50)), as_dict(rank_exact(e, iterations=6, kernel="local")))


def test_auto_counts_vertices_too(spark):
    e = graph(spark, random_edges(3))
    plan = lambda **k: power_loop(weighted(e), ends(e), iterations=1, kernel="auto", **k)._jdf.queryExecution().toString()
    assert "MapInArrow" in plan() and "MapInArrow" not in plan(local_links=10)


def test_eigenvector_summary(spark):
    e = graph(spark, random_edges(5))
    program, start = programs.eigen_centrality(), ends(e).withColumn("value", F.lit(1.0))
    exact = as_dict(programs.run(program, e, 5), "value")
    near(as_dict(programs.run_summary(program, e, ends(e), start, 5), "value"), exact)
    near(as_dict(programs.run_summary(program, e, ends(e).limit(0), start, 5), "value"), dict.fromkeys(exact, 1.0))
    edges, old = random_edges(5), exact
    top = min((v for v in old if v % 2), key=lambda v: (-old[v], v))
    rest, value = sum(old[a] for a, b in edges if b == top), dict(old)
    for _ in range(4):
        got = {v: sum((value[a] if a % 2 == 0 else old[a]) for a, b in edges if b == v) for v in old if v % 2 == 0}
        value |= {v: x / max(rest, *got.values()) for v, x in got.items()}
    before = spark.createDataFrame(list(old.items()), "id bigint, value double")
    near(as_dict(programs.run_summary(program, e, ends(e).where("id % 2 = 0"), before, 4), "value"), value)
    with pytest.raises(ValueError):
        programs.run_summary(programs.shortest_hops(1), e, ends(e), start, 1)


def test_components_of_a_long_chain(spark):
    e = graph(spark, [(k, k + 1) for k in range(64)] + [(1000, 1001), (7000, 7000)])
    assert {r.id: r.component for r in programs.connected(e).collect()} == {**dict.fromkeys(range(65), 0), 1000: 1000, 1001: 1000, 7000: 7000}


@pytest.mark.parametrize("side", [1, 3, 2000])
def test_tau_of_any_length(spark, side):
    import random

    r = random.Random(side)
    a, b = list(range(40)), list(range(20, 60))
    r.shuffle(a), r.shuffle(b)
    listed = lambda x: spark.createDataFrame([(k, i) for k, i in enumerate(x, 1)], "rank bigint, id bigint")
    got = measures.kendall_tau(listed(a), listed(b), 35, side).first()
    both = [(a.index(i), b.index(i)) for i in a[:35] if i in b[:35]]
    minus = sum((x[0] - y[0]) * (x[1] - y[1]) < 0 for n, x in enumerate(both) for y in both[:n])
    assert (got.n_items, got.discordant, got.concordant) == (len(both), minus, len(both) * (len(both) - 1) // 2 - minus)


def test_weights_of_several_chunks(spark, monkeypatch):
    monkeypatch.setattr(measures, "CHUNK", 7)
    for p in (0.9, 1 - 1 / 40):
        got = {r.m: r.w for r in measures._weights(spark, 40, measures._powers(p)).collect()}
        assert got == pytest.approx({m: sum(p ** (d - 1) / d for d in range(m, 41)) for m in range(1, 41)})
    assert measures._sum(lambda d: 0.9**d / d, 3, 40) == pytest.approx(sum(0.9**d / d for d in range(3, 41)))


def test_next_rows_across_ranges(spark):
    rows = [(k % 3, k, 100 + k) for k in range(200)]
    df = spark.createDataFrame(rows, "g bigint, at bigint, v bigint").repartition(5)
    got = {(r.g, r.at): r.next for r in with_next(df, "v", ["at"], ["g"]).collect()}
    assert got == {(g, k): v + 3 if k + 3 < 200 else None for g, k, v in rows}
    assert {r.at: r.next for r in with_next(df, "v", ["at"]).collect()} == {k: v + 1 if k < 199 else None for _, k, v in rows}


def test_batches_of_events_are_joined(spark):
    chain = EventChain(scratch(spark, "chain"))
    batch = lambda ks: spark.createDataFrame([(k, 10 + k) for k in ks], "event_id bigint, user_id bigint").withColumn("ts", F.timestamp_seconds("event_id"))
    found = [{(r.src, r.dst) for r in chain.updates(batch(ks), n).collect()} for n, ks in enumerate(([0, 1], [2, 3], [], [4]))]
    assert found == [{(10, 11)}, {(11, 12), (12, 13)}, set(), {(13, 14)}]
    assert {(r.src, r.dst) for r in chain.updates(batch([2, 3]), 1).collect()} == found[1]  # a batch that is run again


def test_session_compacts_and_cleans(spark):
    edges = graph(spark, random_edges(8, 60, 300))
    session = QuerySession(edges, Params(0.2, 1, 0.5, iterations=3), kernel="local", keep=False, compact=0.02).start()
    known, last = {tuple(r) for r in edges.collect()}, None
    for k in range(4):
        adds = [(200 + k, 3), (k, 200 + k), (k, k + 1)]
        gone = [e for e in sorted(known)[:3] if e not in adds]
        session.run([*(("add", *e) for e in adds), *(("remove", *e) for e in gone)])
        session.query()
        known = known - set(gone) | set(adds)
        assert {tuple(r) for r in session.edges.collect()} == known and session.n_edges == len(known)
        held = len(storage._written)
        assert last is None or held <= last + 3
        last = held
    degrees = {r.id: (r.out_deg, r.in_deg) for r in session.degrees.collect()}
    assert all(degrees[v] == (sum(a == v for a, _ in known), sum(b == v for _, b in known)) for v in degrees)


def test_release_forgets_what_queries_share(spark):
    from hotgraph.catalog import QUERIES, base

    first = QUERIES["deg_out"](spark, SF).count()
    path = next(p for p in storage._written if p.endswith("copurchase"))
    kept, storage._written[:] = [p for p in storage._written if p != path], [path]
    storage.release(spark)
    assert not os.path.exists(path) and not base._memo
    storage._written.extend(kept)
    assert QUERIES["deg_out"](spark, SF).count() == first


def test_cleared_keeps_what_is_wanted(spark):
    first = storage.settle(spark.range(3), "first")
    with storage.cleared(spark) as kept:
        gone = storage.settle(spark.range(4), "gone")
        kept.append(storage.settle(gone, "kept"))
    assert first.count() == 3 and kept[0].count() == 4 and not os.path.exists(gone._settled)
