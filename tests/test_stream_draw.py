"""Streams whose additions and deletions come from one pass over the edges, and sums and changes that read few links twice."""

import hashlib

import numpy as np
import pyarrow as pa
import pytest

from hotgraph.functions import digests
from hotgraph.operators import iterate, updates
from hotgraph.plans import experiment as tasks
from hotgraph.storage import counted, settle

EDGES = sorted({(k, (k * 31 + j * 17) % 1997 + 5000) for k in range(3000) for j in range(3)})


def _key(edge, salt):
    return hashlib.md5(f"{edge[0]}-{edge[1]}-{salt}".encode()).hexdigest(), *edge


def _stream(edges, size, queries, count, order, seed=42):
    added = sorted(edges, key=lambda e: _key(e, seed))[:size]
    added = added if order == "shuffled" else sorted(added)
    since = {e: min(k // (size // queries) + 1, queries) for k, e in enumerate(added)}
    taken, out = set(), {(e, b, "e+") for e, b in since.items()}
    for q in range(1, queries + 1):
        pool = [e for e in edges if since.get(e, 0) < q and e not in taken]
        now = sorted(pool, key=lambda e: _key(e, seed * 1000 + q))[:count]
        taken |= set(now)
        out |= {(e, q, "e-") for e in now}
    return out


@pytest.mark.parametrize("order", ["shuffled", "incidence"])
def test_one_pass_draws_additions_and_deletions(spark, monkeypatch, order):
    written, usual = [], updates.settle
    monkeypatch.setattr(updates, "settle", lambda df, name: written.append(name) or usual(df, name))
    edges = settle(spark.createDataFrame(EDGES, "src bigint, dst bigint"), "edges")
    initial, log = updates.make_stream(edges, 300, 5, 0.3, order=order)
    assert {((r.src, r.dst), r.batch, r.op) for r in log.collect()} == _stream(EDGES, 300, 5, 18, order)
    assert initial.count() == len(EDGES) - 300 and "pool" not in written  # before, the edges were written again and read for the deletions


def test_too_few_under_a_bound_go_the_plain_way(spark, monkeypatch):
    edges = settle(spark.createDataFrame(EDGES, "src bigint, dst bigint"), "edges")
    usual = updates._bound
    for short in (300, 90):  # of the additions, of the deletions
        monkeypatch.setattr(updates, "_bound", lambda size, n, short=short: 1 << 20 if size == short else usual(size, n))
        assert (updates.drawn(edges, 300, 5, 18) is None) == (short == 300)
        _, log = updates.make_stream(edges, 300, 5, 0.3)
        assert {((r.src, r.dst), r.batch, r.op) for r in log.collect()} == _stream(EDGES, 300, 5, 18, "shuffled")


def test_hits_of_many_rows_leave_in_one_batch():
    rows = [pa.RecordBatch.from_arrays([pa.array([a for a, _ in part]), pa.array([b for _, b in part]), pa.array([k % 3 for k in range(len(part))], pa.int32())], ["src", "dst", "since"])
            for part in (EDGES[:500], EDGES[500:900])]
    salts, bounds = ["42", "42001", "42002", "7"], [1 << 29, 1 << 30, 1 << 28, 1 << 31]
    out = list(digests.pairs_below(salts, bounds, 1)(iter(rows)))
    got = {(s, d, q) for b in out for s, d, q in zip(*(b.column(k).to_pylist() for k in range(3)), strict=True)}
    since = [*(k % 3 for k in range(500)), *(k % 3 for k in range(400))]
    assert got == {(*e, q + 1) for e, s in zip(EDGES[:900], since, strict=True) for q in range(4) if s <= q and int(_key(e, salts[q])[0][:8], 16) < bounds[q]}
    assert len(out) == 1


def test_sums_by_degree_and_cuts_change_nothing(monkeypatch):
    made, n = np.random.default_rng(6), 3000
    a, b = made.integers(0, n, (2, 60_000))
    b[:20_000] = b[:20_000] ** 2 // n // 50  # targets with many sources, no two with as many
    s, values = tasks.State(a, b, n), made.random(n)
    assert s.size < tasks.FEW_LINKS
    plain = tasks.collector(s.into, s.back)(values)
    for alike, block in ((2, 1 << 17), (30, 500), (10**9, 500)):
        monkeypatch.setattr(tasks, "FEW_LINKS", 0)
        monkeypatch.setattr(tasks, "ALIKE", alike)
        monkeypatch.setattr(tasks, "BLOCK", block)
        np.testing.assert_allclose(tasks.collector(s.into, s.back)(values), plain, rtol=1e-13)
    x, out = s.dst, np.sort(made.choice(s.size, 40, replace=False))
    at, new = np.sort(np.concatenate([out[:9], out[:4], [0, s.size], made.integers(0, s.size, 30)])), made.integers(0, n, 45)
    want = [y for p in range(s.size + 1) for y in [*new[at == p].tolist(), *([] if p == s.size or p in out else [x[p]])]]
    for sparse in (1, 10**6):
        monkeypatch.setattr(tasks, "SPARSE", sparse)
        got = tasks._spliced(x, out, at, new)
        assert got.tolist() == want and got.dtype == x.dtype


def test_written_rows_are_counted_once(spark):
    df = settle(spark.range(7), "seven")
    assert counted(df) == 7 and iterate.fits(7, df) and not iterate.fits(6, df, spark.range(1))
    df.count = None  # not called again
    assert counted(df) == 7 and iterate.fits(7, df, spark.range(2))
