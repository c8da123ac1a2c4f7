"""Streams with many deletions come from one pass over the edges, made once for both orders."""

from hotgraph.operators import updates
from hotgraph.storage import settle
from tests.test_stream_draw import EDGES, _stream


def test_many_deletions_still_come_from_one_pass(spark, monkeypatch):
    monkeypatch.setattr(updates, "MOST_PICKS", 200)  # before, 18 * 5 * 5 keys were held to be needed, and each chunk read all edges
    read, usual = [], updates.settle
    monkeypatch.setattr(updates, "settle", lambda df, name: read.append(name) or usual(df, name))
    edges = settle(spark.createDataFrame(EDGES, "src bigint, dst bigint"), "edges")
    for order in ("shuffled", "incidence"):
        _, log = updates.make_stream(edges, 300, 5, 0.3, order=order)
        assert {((r.src, r.dst), r.batch, r.op) for r in log.collect()} == _stream(EDGES, 300, 5, 18, order)
    assert read.count("low") == 1 and read.count("deleted") == 2 and "pool" not in read
