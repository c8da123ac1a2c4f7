"""Replays on larger graphs: exact answers made once for all sets, few bytes an edge, keys hashed together."""

import hashlib

import numpy as np
import pyarrow as pa

from hotgraph.functions import digests
from hotgraph.operators.localhot import hot_of
from hotgraph.plans import experiment as tasks
from hotgraph.plans.workloads import grid, workload
from hotgraph.schema import Params

SF = "/root/testdata/sf0.001"


def test_digests_under_a_bound(monkeypatch):
    monkeypatch.setattr(digests, "LANES", 50)
    made = np.random.default_rng(5)
    texts = [f"{a}-{b}" for a, b in made.integers(-(10**18), 10**18, (60, 2))] + [f"{a}-{b}" for a, b in made.integers(0, 10**5, (400, 2))]
    salts, bound = [b"-42001", b"-42002", b"-" + b"7" * 20, b""], 3 << 29
    head = lambda x: int(hashlib.md5(x).hexdigest()[:8], 16)  # noqa: E731, S324
    for part in (pa.array(texts), pa.array(texts).slice(7, 300)):
        got = {(k, int(i)) for k, rows in digests.below(part, salts, bound) for i in rows}
        assert got == {(k, i) for k, salt in enumerate(salts) for i, x in enumerate(part.to_pylist()) if head(x.encode() + salt) < bound}


def test_exact_answers_are_made_once_for_all_sets(spark):
    work = workload(spark, SF, "social", 11, chunk=3, deletion_ratio=0.34)
    sets = [Params(0.2, 0, 0.5, iterations=4), Params(0.05, 2, 1.0, iterations=4), Params(0.05, 2, 1.0, iterations=3, max_hops=2)]
    runs = {(r.set_id, r.query, r.metric): r.value for r in tasks.experiment(work.initial, work.updates, sets, 11).collect()}
    a, b, c = (p.label for p in sets)
    assert all(runs[a, q, "seconds_exact"] == runs[b, q, "seconds_exact"] != runs[c, q, "seconds_exact"] for q in range(1, 12))
    assert {q for _, q, m in runs if m == "rbo_full"} == {10} and {q for _, q, m in runs if m == "rbo_wide"} == set(range(1, 12))


def _streams(n=40, queries=5, seed=4):
    made = np.random.default_rng(seed)
    pairs = lambda k: np.unique([a * n + b for a, b in made.integers(0, n, (k, 2)) if a != b])
    return pairs(200), {q: (pairs(15), pairs(25)) for q in range(1, queries + 1)}, n


def test_a_share_of_the_answers_starts_where_the_one_before_ends():
    keys, updates, n = _streams()
    p = Params(iterations=7)
    whole = {q: x for q, _, x in tasks.answers(tasks.State(*np.divmod(keys, n), n), updates, p, 1, 5)}
    for first, last in ((2, 2), (4, 5)):
        for q, _, x in tasks.answers(tasks.State(*np.divmod(keys, n), n), updates, p, first, last):
            assert (x == whole[q]).all()
    edges, score = {divmod(int(k), n) for k in keys}, None
    for q in range(1, 6):
        plus, minus = ({divmod(int(k), n) for k in x} for x in updates[q])
        edges = edges - minus | plus
        score = np.ones(n)
        for _ in range(7):
            score = 0.15 + 0.85 * np.array([sum(score[a] / sum(x == a for x, _ in edges) for a, b in edges if b == v) for v in range(n)])
        np.testing.assert_allclose(whole[q], score, atol=1e-12)


def test_blocks_and_few_aimed_edges_change_nothing(monkeypatch):
    monkeypatch.setattr(tasks, "PACK", 16)
    keys, updates, n = _streams()
    p = Params(0.2, 1, 0.5, iterations=6)

    def replayed():
        truth, s = tasks.Truth(5), tasks.State(*np.divmod(keys, n), n)
        for q, spent, x in tasks.answers(tasks.State(*np.divmod(keys, n), n), updates, p, 1, 5):
            for k in range(0, n, 16):
                truth.put(q, k // 16, spent, x[k : k + 16].tobytes())
        return {(q, m): v for q, m, v in tasks.replay_set(s, updates, np.arange(n), p, 5, truth) if not m.startswith(("seconds", "speedup"))}

    usual = replayed()
    monkeypatch.setattr(tasks, "WHOLE", 0)
    monkeypatch.setattr(tasks, "BLOCK", 7)
    monkeypatch.setattr(tasks, "SORTED", 30)
    blocks = replayed()
    assert usual.keys() == blocks.keys() and all(abs(usual[k] - blocks[k]) < 1e-9 for k in usual)
    s, hot = tasks.State(*np.divmod(keys, n), n), np.arange(n) % 20 == 3
    for mark in (hot, ~hot):
        ids = np.flatnonzero(mark)
        assert tasks._aimed(s, mark, ids, s.into[ids]).tolist() == [a for b in ids for a in sorted(s.src[s.dst == b])]


def test_hops_by_degrees_need_no_sources():
    keys, _, n = _streams(seed=8)
    s = tasks.State(*np.divmod(keys, n), n)
    prev = np.where(np.arange(n) % 9 == 0, -1, s.out)
    for p in (Params(0.2, 6, 0.5), Params(0.2, 1, 0.01), Params(0.2, 0, None)):
        plain, lean = (hot_of(src, s.dst, np.arange(n), prev, s.out, np.ones(n), p, None, s.out, s.into) for src in (s.src, None))
        listed = hot_of(s.src, s.dst, np.arange(n), prev, s.out, np.ones(n), p)
        assert all(a.tolist() == b.tolist() == c.tolist() for a, b, c in zip(plain, lean, listed, strict=True))


def test_ids_are_numbered_close_or_far():
    for ids in (np.array([5, 9, 6, -3, 9]), np.array([5, 10**17, -(10**18), 5]), np.empty(0, np.int64)):
        known, number = tasks._numbers([ids, ids[:2].astype(np.int64)])
        assert known.tolist() == sorted(set(ids.tolist()))
        assert not ids.size or number(ids).tolist() == [sorted(set(ids.tolist())).index(x) for x in ids.tolist()]
    score, there = np.array([3.0, 1.0, 2.0, 2.0, 9.0]), np.array([True, True, True, True, False])
    assert [tasks.ranking(score, there, k).tolist() for k in (1, 2, 3, None)] == [[0], [0, 2], [0, 2, 3], [0, 2, 3, 1]]


def test_a_graph_is_built_in_few_bytes(monkeypatch):
    import tracemalloc

    monkeypatch.setattr(tasks, "SORTED", 1 << 15)
    made, n, held = np.random.default_rng(2), 5000, tasks.Stream(1)
    for _ in range(20):
        held.start.append(made.integers(0, n, (20_000, 2)).astype(np.int32))
    edges = np.unique(np.concatenate(list(held.start)).astype(np.int64) @ [n, 1])
    tracemalloc.start()
    s, _, ids = held.open()
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert ids.tolist() == list(range(n)) and (s.src * np.int64(n) + s.dst == edges).all()
    assert most < 20 * 400_000  # with the keys of all edges, 30 bytes of each


def _replayed(spark, monkeypatch, sf, name):
    """Sets that a query replays on each graph, with the replay left out."""
    from hotgraph.catalog import QUERIES, workloads

    seen = []
    work = lambda spark, sf, name, queries, *, edges, **more: (name, edges, more)
    row = lambda work, sets: seen.append((*work, [p.label for p in sets])) or spark.createDataFrame([(work[0], p.label, 1, "rbo", 0.5) for p in sets], tasks.RUNS)
    monkeypatch.setattr(workloads, "edges_of", lambda spark, sf, name, both_ways: object())
    monkeypatch.setattr(workloads, "workload", work)
    monkeypatch.setattr(workloads, "ran", row)
    return QUERIES[name](spark, sf), seen


def test_accuracy_grid_replays_its_own_sets(spark, monkeypatch):
    found, seen = _replayed(spark, monkeypatch, "none/accuracy", "workload_accuracy_grid")
    assert sorted(s[0] for s in seen) == ["copurchase", "social", "web"] and all(s[3] == [p.label for p in grid("accuracy")] for s in seen)
    assert {(r.graph, r.set_id) for r in found.collect()} == {(g, p.label) for g in ("copurchase", "social", "web") for p in grid("accuracy")}


def test_speed_grid_takes_runs_of_all_sets_where_there_are_some(spark, monkeypatch):
    found, seen = _replayed(spark, monkeypatch, "none/speed", "workload_speed_grid")
    assert all(s[3] == [p.label for p in grid("speed")] for s in seen) and found.count() == 15
    _, seen = _replayed(spark, monkeypatch, "none/both", "experiment_report")
    found, more = _replayed(spark, monkeypatch, "none/both", "workload_speed_grid")
    assert len(seen) == 3 and not more and found.count() == 15


def test_deletions_start_from_one_graph(spark, monkeypatch):
    found, seen = _replayed(spark, monkeypatch, "none/deletions", "workload_deletions")
    assert len(seen) == 4 and len({id(s[1]) for s in seen}) == 2 and sorted(s[2]["deletion_ratio"] for s in seen) == [0.0, 0.0, 0.2, 0.2]
    assert found.select("graph").distinct().count() == 4 and found.count() == 36


def test_report_replays_several_graphs_at_a_time(spark, monkeypatch):
    from hotgraph.catalog import workloads

    given, usual = [], workloads._together
    monkeypatch.setattr(workloads, "_together", lambda makes: given.append(len(makes)) or usual(makes))
    found, seen = _replayed(spark, monkeypatch, "none/report", "experiment_report")
    assert given == [3] and len(seen) == 3 and found.count() == 27
