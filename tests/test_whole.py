"""Jobs that end by themselves, not at a fixed depth or size."""

import pytest

from hotgraph.operators import programs
from hotgraph.operators.selection import expand_by_influence


def test_hops_on_a_long_chain(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(16)] + [(20, 21)], "src bigint, dst bigint")
    found = programs.run(programs.shortest_hops(0), edges, None).where("value is not null")
    assert {(r.id, r.value) for r in found.collect()} == {(k, k) for k in range(17)}


@pytest.mark.parametrize("mode, last", [("candidate", 13), ("anchor", 13), ("path_product", 14)])
def test_influence_ring_ends_by_itself(spark, mode, last):
    """A chain of out-degree 1: contributions never dilute, and budgets last as long as the score allows."""
    edges = spark.createDataFrame([(k, k + 1) for k in range(14)] + [(20, k) for k in range(21, 31)], "src bigint, dst bigint")
    scores = spark.createDataFrame([(k, 5.0) for k in range(31)], "id bigint, score double")
    anchor = edges.where("src = 0").selectExpr("src as id")
    found = expand_by_influence(edges, anchor, anchor, scores, 0.1, mean=1.38, mode=mode)
    assert sorted((r.id, r.hop) for r in found.collect()) == [(k, k) for k in range(1, last + 1)]
