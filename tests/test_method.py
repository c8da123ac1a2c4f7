"""Worked examples, invariants on random graphs, and measures against plain loops."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from hotgraph.functions.expressions import influence_budget, within_budget
from hotgraph.operators import measures, updates
from hotgraph.operators.iterate import power_loop, rank_exact, weighted
from hotgraph.operators.ranks import global_rank, list_length, top
from hotgraph.operators.selection import expand_by_influence, expand_hops, select_changed, select_hot
from hotgraph.operators.stats import degree_change, degrees, mean_degree
from hotgraph.operators.summary import build_summary, outside_total, rank_approximate
from hotgraph.schema import Params, require
from hotgraph.sources.graphs import ends
from tests import reference as ref

H1 = [(1, 2), (2, 3), (3, 1), (1, 3)]
RING = [(1, 2), (2, 3), (3, 4), (4, 5), (5, 1)]


def graph(spark, edges):
    return spark.createDataFrame(list(edges), "src bigint, dst bigint")


def as_dict(df, value="score"):
    return {r["id"]: r[value] for r in df.collect()}


def near(a, b, by=1e-9):
    assert a.keys() == b.keys()
    for k in a:
        assert a[k] == pytest.approx(b[k], abs=by), k


def random_edges(seed, n=40, m=140):
    r = random.Random(seed)
    return {(a, b) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(m)) if a != b}


@pytest.mark.parametrize("kernel", ["distributed", "local"])
def test_triangle_with_chord(spark, kernel):
    near(as_dict(rank_exact(graph(spark, H1), kernel=kernel)), {1: 1.163369, 2: 0.644432, 3: 1.192199}, 1e-6)


@pytest.mark.parametrize(("n", "want"), [
    (0, {1: 1.0, 2: 1.0, 3: 1.0, 4: 1.0, 5: 1.0, 6: 0.575}), (1, {1: 1.0, 2: 0.575, 3: 1.0, 4: 1.0, 5: 1.0, 6: 0.575}),
    (2, {1: 1.0, 2: 0.575, 3: 0.63875, 4: 1.0, 5: 1.0, 6: 0.575}),
])
def test_ring_with_new_vertex(spark, n, want):
    before, now = graph(spark, RING), graph(spark, [*RING, (1, 6)])
    old = rank_exact(before, kernel="local")
    near(as_dict(old), dict.fromkeys(range(1, 6), 1.0))
    hot = select_hot(now, before, old, Params(0.2, n, None))
    assert {r.id for r in hot.collect()} == [{1, 6}, {1, 2, 6}, {1, 2, 3, 6}][n]
    built = build_summary(now, hot, old)
    assert {(r.src, r.dst): r.weight for r in built.inner.collect()}[1, 6] == 0.5
    assert outside_total(built).first()["outside_total"] == pytest.approx(1.0)
    near(as_dict(rank_approximate(built, old, ends(now), kernel="local")), want)


def test_seeds_of_the_ring(spark):
    change = degree_change(graph(spark, RING), graph(spark, [*RING, (1, 6)]))
    assert {r.id: r.reason for r in select_changed(change, 0.5).collect()} == {1: "changed", 6: "new"}
    assert {r.id for r in select_changed(change, 1.0).collect()} == {6}


def test_degree_rules(spark):
    rows = [(1, 0, 1), (2, 1, 0), (3, 0, 0), (4, None, 0), (5, 10, 12), (6, 10, 8)]
    change = spark.createDataFrame(rows, "id bigint, deg_prev bigint, deg_now bigint")
    pick = lambda r, **k: {x.id for x in select_changed(change, r, **k).collect()}
    assert pick(0.5) == {1, 2, 4} and pick(1.0) == {1, 4} and pick(0.1) == {1, 2, 4, 5, 6} and pick(0.2) == {1, 2, 4}
    assert pick(-1.0) == {1, 2, 3, 4, 5, 6} and pick(0.5, zero_policy="exclude") == {2, 4}


def test_budget(spark):
    row = spark.createDataFrame([(2.0, 2, 4.0)], "s double, d bigint, m double")
    got = row.select(influence_budget("s", "d", "m", 0.5), *(within_budget(F.lit(h), "s", "d", "m", 0.5) for h in (1.0, 2.0))).first()
    assert got[0] == pytest.approx(1.5) and got[1] and not got[2]


def test_no_updates_and_isolated_vertices(spark):
    e = graph(spark, RING)
    old = rank_exact(e, kernel="local")
    assert select_hot(e, e, old, Params(0.2, 1, 0.5)).count() == 0
    lonely = ends(e).union(spark.createDataFrame([(9,)], "id bigint"))
    assert as_dict(rank_exact(e, vertices=lonely, kernel="local"))[9] == pytest.approx(0.15)


def test_updates_are_set_operations(spark):
    e = graph(spark, RING)
    pairs = lambda df: {(r.src, r.dst) for r in df.collect()}
    log = spark.createDataFrame([(1, 1, "e+", 1, 2), (2, 2, "e-", 7, 8), (3, 3, "e+", 1, 3), (4, 4, "e-", 1, 3), (5, 5, "e-", 2, 3)], "seq bigint, ts bigint, op string, src bigint, dst bigint")
    assert pairs(updates.merge_updates(e, *updates.net_changes(log))) == set(RING) - {(2, 3)} | {(1, 3)}
    assert pairs(updates.merge_updates(e, *updates.net_changes(log, "last_wins"))) == set(RING) - {(2, 3)}


@pytest.mark.parametrize("seed", [1, 2])
def test_random_graphs(spark, seed):
    before = random_edges(seed)
    r = random.Random(seed)
    gone = set(r.sample(sorted(before), 4))
    now = before - gone | {(r.randrange(45), r.randrange(45)) for _ in range(6)}
    now = {(a, b) for a, b in now if a != b}
    verts = ref.vertices(before) | ref.vertices(now)
    b, e = graph(spark, before), graph(spark, now)
    v = spark.createDataFrame([(x,) for x in verts], "id bigint")
    old = rank_exact(b, kernel="local")
    near(as_dict(old), ref.rank(before))
    near(as_dict(rank_exact(b, iterations=7)), ref.rank(before, rounds=7))
    sets = [{x.id for x in select_hot(e, b, old, p).collect()} for p in (Params(0.2, 0, None), Params(0.2, 1, None), Params(0.2, 2, None), Params(0.2, 1, 1.0), Params(0.2, 1, 0.1))]
    assert sets[0] <= sets[1] <= sets[2] and sets[1] <= sets[3] <= sets[4]
    assert {x.id for x in select_hot(e, b, old, Params(0.05, 0, None)).collect()} >= sets[0]
    seeds = spark.createDataFrame([(x,) for x in sets[0]], "id bigint")
    assert as_dict(expand_hops(e, seeds, 2), "hop") == ref.hops(now, sets[0], 2)
    hot = spark.createDataFrame([(x,) for x in sets[3]], "id bigint")
    built = build_summary(e, hot, old)
    near(as_dict(rank_approximate(built, old, v, kernel="local")), ref.approximate(now, sets[3], ref.rank(before), verts))
    near(as_dict(rank_approximate(built, old, v, iterations=6)), ref.approximate(now, sets[3], ref.rank(before), verts, rounds=6))
    assert {x.dst for x in built.inner.collect()} | {x.dst for x in built.inflow.collect()} <= sets[3]
    every = build_summary(e, v, old)
    near(as_dict(rank_approximate(every, old, v, warm=False, kernel="local")), ref.rank(now, verts))
    none = build_summary(e, hot.limit(0), old)
    held = as_dict(old)
    near(as_dict(rank_approximate(none, old, v, kernel="local")), {x: held.get(x, 0.15) for x in verts})


def test_exact_cold_scores_leave_no_error(spark):
    edges = random_edges(9)
    e = graph(spark, edges)
    fixed = rank_exact(e, iterations=400, kernel="local")
    hot = ends(e).where("id % 3 = 0")
    near(as_dict(rank_approximate(build_summary(e, hot, fixed), fixed, ends(e), kernel="local")), as_dict(fixed), 1e-8)


def test_ring_anchor_readings_agree_beyond_the_seeds(spark):
    before = random_edges(4)
    e, b = graph(spark, before | {(1, 30), (2, 31)}), graph(spark, before)
    old = rank_exact(b, kernel="local")
    hot = lambda **k: {r.id for r in select_hot(e, b, old, Params(0.2, 1, 0.3, **k)).collect()}
    assert hot(anchor="ring") == hot(anchor="seeds+ring")
    core = {r.id for r in select_hot(e, b, old, Params(0.2, 1, None)).collect()}
    assert all(hot(**k) >= core for k in ({"mode": "anchor"}, {"mode": "path_product"}, {"threshold": "relative"}, {"mean_degree": "touched"}))


def test_sparse_graph_is_outside_the_formula(spark):
    chain = [(k, k + 1) for k in range(10)]
    e = graph(spark, chain)
    scores = rank_exact(e, kernel="local")
    one = spark.createDataFrame([(3,)], "id bigint")
    found = expand_by_influence(e, one, one, scores, 0.5, mean=mean_degree(e).first()["mean_degree"])
    assert {r.id: r.hop for r in found.collect()} == {4: 1}


def test_loop_options(spark):
    edges = random_edges(6) | {(1, 99)}
    e = graph(spark, edges)
    assert set(as_dict(rank_exact(e, beta=0.0, iterations=1, kernel="local")).values()) == {1.0}
    both = [as_dict(rank_exact(e, iterations=8, dangling="redistribute", kernel=k)) for k in ("local", "distributed")]
    near(*both)
    assert sum(both[0].values()) == pytest.approx(len(both[0]))
    n = len(both[0])
    near({k: v * n for k, v in as_dict(rank_exact(e, iterations=8, normalize=True, kernel="local")).items()}, as_dict(rank_exact(e, iterations=8, kernel="local")))
    slow = as_dict(power_loop(weighted(e), ends(e), iterations=300, tol=1e-12, kernel="distributed", norm="linf"))
    near(slow, as_dict(rank_exact(e, iterations=300, kernel="local")), 1e-9)
    with pytest.raises(ValueError):
        rank_exact(e, beta=1.5)


def ranking(spark, ids):
    return spark.createDataFrame([(k + 1, x) for k, x in enumerate(ids)], "rank bigint, id bigint")


def test_overlap_measures(spark):
    r = random.Random(3)
    a = list(range(30))
    b = a[:]
    r.shuffle(b)
    x, y = ranking(spark, a), ranking(spark, b)
    for p in (0.5, 0.9, 0.98):
        base = ref.overlap(a, b, 30, p)
        assert measures.rbo(x, y, 30, p, "base").first()["rbo"] == pytest.approx(base, abs=1e-12)
        assert measures.rbo(x, y, 30, p).first()["rbo"] == pytest.approx(base + p**30, abs=1e-12)
        assert measures.rbo(x, x, 30, p).first()["rbo"] == pytest.approx(1)
        low, rest = (measures.rbo(x, y, 20, p, f).first()["rbo"] for f in ("min", "res"))
        assert low - 1e-12 <= measures.rbo(x, y, 20, p).first()["rbo"] <= low + rest + 1e-12
        assert measures.rbo_uneven(ranking(spark, b[:12]), x, 12, 30, p).first()["rbo"] == pytest.approx(ref.extrapolated_uneven(b[:12], a, p), abs=1e-12)
    apart = ranking(spark, range(100, 130))
    assert measures.rbo(x, apart, 30).first()["rbo"] == 0
    head, tail = a[:], a[:]
    head[0], head[1], tail[28], tail[29] = head[1], head[0], tail[29], tail[28]
    value = lambda z: measures.rbo(x, ranking(spark, z), 30, 0.9).first()["rbo"]
    assert value(head) < value(tail)
    assert measures.kendall_tau(x, ranking(spark, a[::-1]), 30).first()["tau"] == -1


def test_ranks(spark):
    df = spark.createDataFrame([(k, (k * 7) % 5 / 4) for k in range(50)], "id bigint, score double")
    want = [k for _, k in sorted((-((k * 7) % 5) / 4, k) for k in range(50))]
    assert [r.id for r in sorted(global_rank(df, partitions=3).collect(), key=lambda r: r["rank"])] == want
    assert [r.id for r in top(df, 7).orderBy("rank").collect()] == want[:7]
    assert list_length(5) == 5 and list_length(50) == 10 and list_length(1234) == 124


def test_stream_making(spark):
    edges = random_edges(8, 60, 400)
    initial, log = updates.make_stream(graph(spark, edges), 40, 4, 0.2)
    start, rows = {(r.src, r.dst) for r in initial.collect()}, log.collect()
    adds = {(r.src, r.dst): r.batch for r in rows if r.op == "e+"}
    assert len(adds) == 40 and start == edges - set(adds)
    gone = [(r.src, r.dst, r.batch) for r in rows if r.op == "e-"]
    assert len(gone) == 8 and len({g[:2] for g in gone}) == 8
    assert all(g[:2] in start or adds[g[:2]] < g[2] for g in gone)
    again = updates.make_stream(graph(spark, edges), 40, 4, 0.2)[1].collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again))


def test_degrees_and_schema(spark):
    e = graph(spark, H1)
    assert as_dict(degrees(e, "in"), "degree") == {1: 1, 2: 1, 3: 2}
    with pytest.raises(ValueError):
        require(e, "src string, dst bigint")
    for bad in ({"r": -1}, {"n": -1}, {"delta": 0}, {"beta": 2}, {"mode": "x"}):
        with pytest.raises(ValueError):
            Params(**bad)


@pytest.mark.parametrize("block", [3, 2048])
def test_nearest_by_any_blocks(spark, block):
    """Blocks of any size against all pairs; null, zero and equal vectors included."""
    from hotgraph.operators.neighbours import nearest

    rng = np.random.default_rng(5)
    vectors = {k: [float(x) for x in rng.integers(-3, 4, 4)] for k in range(40)} | {40: [0.0] * 4, 41: [1.0, 0.0, 0.0, 2.0], 42: [1.0, 0.0, 0.0, 2.0]}
    frame = spark.createDataFrame([*vectors.items(), (43, None)], "vec_id bigint, embedding array<double>")
    real = {k: np.array(v) / np.linalg.norm(v) for k, v in vectors.items() if any(v)}
    want = {
        (a, b) for a in real for b in sorted((b for b in real if b != a), key=lambda b: (-round(float(real[a] @ real[b]), 9), b))[:3]
    }
    assert {(r.src, r.dst) for r in nearest(frame, 3, block).collect()} == want
    assert nearest(frame.limit(0), 3, block).count() == 0
