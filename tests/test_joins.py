"""Joins at size: what is copied, what is broadcast, which order counts."""

from hotgraph.catalog import QUERIES
from hotgraph.operators import joins


def test_salted_join_copies_hot_keys_only_and_broadcasts_nothing(spark):
    left = spark.createDataFrame([(0, k) for k in range(400)] + [(k, k) for k in range(1, 600)] + [(None, 1)], "k bigint, x bigint")
    right = spark.createDataFrame([(k, f"p{k}") for k in range(1000)], "k bigint, p string")
    met = joins.salted_join(left, right, "k", 8)
    rows = [tuple(r) for r in met.collect()]
    assert sorted(rows) == sorted([(0, k, "p0") for k in range(400)] + [(k, k, f"p{k}") for k in range(1, 600)])
    plan = met._jdf.queryExecution().executedPlan()
    assert "Broadcast" not in plan.toString() and "SortMergeJoin" in plan.toString()
    made = [n for n in _nodes(plan) if n.nodeName() == "Generate"]
    assert [n.metrics().apply("numOutputRows").value() for n in made] == [1007]


def _nodes(plan):
    """Nodes of a physical plan, those of adaptive stages included."""
    inner = [plan.executedPlan()] if plan.nodeName() == "AdaptiveSparkPlan" else [plan.plan()] if "QueryStage" in plan.nodeName() else []
    below = plan.children()
    out = [plan]
    for node in [*inner, *(below.apply(k) for k in range(below.size()))]:
        out += _nodes(node)
    return out


def test_lateral_topk_on_shuffled_orders(spark, tmp_path):
    """Orders in many parts and many to a customer: the dearest two, whatever way the rows come."""
    orders = spark.range(60_000).selectExpr("id as o_orderkey", "id % 50 as o_custkey", "cast((id * 7919) % 60013 as double) as o_totalprice")
    orders.repartition(16).write.parquet(f"{tmp_path}/orders.parquet")
    spark.range(50).withColumnRenamed("id", "c_custkey").write.parquet(f"{tmp_path}/customer.parquet")
    want = []
    for c in range(50):
        mine = sorted(((-((k * 7919) % 60013), k) for k in range(c, 60_000, 50)))
        want += [(c, k) for _, k in mine[:2]]
    df = QUERIES["join_lateral_topk"](spark, str(tmp_path))
    assert sorted((r.c_custkey, r.o_orderkey) for r in df.collect()) == sorted(want)
    window = [line for line in df._jdf.queryExecution().optimizedPlan().toString().splitlines() if "windowspecdefinition" in line]
    assert len(window) == 1 and "o_totalprice" in window[0] and "DESC" in window[0]  # not the order in which rows happen to come
