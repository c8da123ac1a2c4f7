"""Queries against their DuckDB oracles on the smallest tables."""

import math

import duckdb
import pytest

from hotgraph.catalog import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One or two of each kind; the driver compares all of them.
PICKED = [
    "graph_copurchase", "graph_social", "graph_web", "graph_user_next", "graph_knn", "deg_total", "components_minlabel", "rank_exact_sinks",
    "rank_dangling", "seeds_changed", "ring_hops_2", "ring_influence_candidate", "ring_influence_anchor", "ring_path_product", "hot_set",
    "summary_boundary", "outside_total", "summary_ratio", "rank_approximate", "rank_approx_all_hot", "replay_final_scores", "sssp_hops",
    "label_communities", "rbo_ext", "rbo_res", "rbo_uneven", "kendall_tau", "best_worst_sets", "stream_deletions", "apply_last_wins",
    "update_stats", "degree_rolled", "join_asof_last_event", "join_interval", "join_skew_salted", "agg_cube", "agg_percentile_exact",
    "win_sessionize", "global_rank_distributed", "set_except_all", "sub_not_in_null", "arr_set_ops", "json_extract", "st_sliding",
    "st_session", "st_watermark_late", "udtf_walk_expand", "st_late_side_table", "st_query_loop", "experiment_work", "experiment_scores",
    "experiment_rbo", "eigen_summary", "page_rank_summary", "hot_set_touched_mean", "hot_set_score_change", "ring_hops_in", "ring_hops_both",
]


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return None
    if hasattr(v, "isoformat"):
        return str(v)
    return round(v, 5) + 0.0 if isinstance(v, float) else v


@pytest.mark.parametrize("name", PICKED)
def test_against_oracle(spark, name):
    df = QUERIES[name](spark, SF)
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    found = db.execute(ORACLES[name])
    columns = [c[0] for c in found.description]
    assert sorted(columns) == sorted(df.columns)
    want = sorted(([plain(v) for v in r] for r in found.fetchall()), key=repr)
    assert sorted(([plain(r[c]) for c in columns] for r in df.collect()), key=repr) == want


def test_every_query_is_registered():
    import __spark_entry__ as entry

    assert set(QUERIES) <= set(entry.queries()) and set(entry.oracle_sql()) <= set(entry.queries())


def _python(code, cwd):
    import subprocess
    import sys

    return subprocess.run([sys.executable, "-B", "-c", code], cwd=cwd, capture_output=True, text=True, timeout=120)


def test_entry_imports_without_a_session_and_without_the_training_data_operators(tmp_path):
    import os
    import shutil

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; print(len(e.queries()), set(e.oracle_sql()) <= set(e.queries()))"
    assert _python(code, root).stdout.split()[1] == "True"
    copy = tmp_path / "copy"
    shutil.copytree(os.path.join(root, "hotgraph"), copy / "hotgraph", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(root, "__spark_entry__.py"), copy)
    done = _python(code, copy)
    assert done.stdout.split() == [str(len(QUERIES)), "True"], done.stderr[-500:]
