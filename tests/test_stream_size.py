"""Streams and replays on larger graphs: few keys are sorted, one set is dealt to each task, and results stay the same."""

import hashlib
from types import SimpleNamespace

import numpy as np

from hotgraph.operators import updates
from hotgraph.plans import workloads
from hotgraph.plans.experiment import State


def _picked(initial, additions, queries, count, seed=42):
    taken, out = set(), set()
    for q in range(1, queries + 1):
        pool = [e for e in initial | {(s, d) for s, d, b in additions if b < q} if e not in taken]
        now = sorted(pool, key=lambda e: (hashlib.md5(f"{e[0]}-{e[1]}-{seed * 1000 + q}".encode()).hexdigest(), *e))[:count]
        taken |= set(now)
        out |= {(*e, q) for e in now}
    return out


def test_deletions_sort_only_keys_under_a_bound(spark):
    initial = {(k, (k * 31 + j) % 997 + 5000) for k in range(2000) for j in range(3)}
    additions = {(k, 9000 + k, 1 + k % 5) for k in range(50)}
    frames = spark.createDataFrame(sorted(initial), "src bigint, dst bigint"), spark.createDataFrame(sorted(additions), "src bigint, dst bigint, batch int")
    got = updates.sample_deletions(*frames, 5, 4)
    assert {tuple(r) for r in got.select("src", "dst", "batch").collect()} == _picked(initial, additions, 5, 4)
    keyed = spark.range(100_000).selectExpr("id", "1 as batch", "md5(cast(string(id) as binary)) as key")
    low = updates._low(keyed, 20, 1, 100_000)
    assert 20 <= low.count() < 2000
    assert [r.id for r in low.orderBy("key").limit(20).collect()] == [r.id for r in keyed.orderBy("key").limit(20).collect()]
    skewed = keyed.selectExpr("id", "batch", "concat('f', key) as key")
    assert updates._low(skewed, 20, 1, 100_000).count() == 100_000  # too few under the bound: all stay


def test_degrees_follow_the_edges():
    n, made = 50, np.random.default_rng(3)
    edges = {(int(a), int(b)) for a, b in made.integers(0, n, (300, 2)) if a != b}
    s = State(*map(np.array, zip(*sorted(edges), strict=True)), n)
    for _ in range(6):
        out = s.out
        was = out.copy()
        plus, minus = ({(int(a), int(b)) for a, b in made.integers(0, n, (40, 2)) if a != b} for _ in range(2))
        key = lambda pairs: np.unique([a * n + b for a, b in pairs])
        s.apply(key(plus), key(minus))
        edges = edges - minus | plus
        assert list(zip(s.src.tolist(), s.dst.tolist(), strict=True)) == sorted(edges)
        assert s.out.tolist() == np.bincount(s.src, minlength=n).tolist() and s.into.tolist() == np.bincount(s.dst, minlength=n).tolist()
        assert (out == was).all()  # degrees of the query before are still needed


def test_scaling_ranks_the_first_graph_once(spark, monkeypatch):
    given, usual = [], spark.conf.get("spark.sql.shuffle.partitions")

    def replay(work, params, strategy, *, kernel, first=None):
        given.append((spark.conf.get("spark.sql.shuffle.partitions"), strategy, kernel, first))
        return SimpleNamespace(rows=[{"phases": {"ingest": 1.0, "compute": 2.0}}]), [first or "ranked", "answer"]

    monkeypatch.setattr(workloads, "replay", replay)
    found = workloads.scaling(SimpleNamespace(initial=spark.range(1)), [2, 4])
    assert [g[3] for g in given] == [None, "ranked", "ranked", "ranked"] and {g[2] for g in given} == {"distributed"}
    assert [g[0] for g in given] == ["2", "2", "4", "4"] and spark.conf.get("spark.sql.shuffle.partitions") == usual
    assert found.count() == 12 and found.agg({"seconds": "sum"}).first()[0] == 12.0
