"""Queries whose job runs over a given table, and not over rows made up in the code."""

import duckdb
import pytest

from hotgraph.catalog import ORACLES, QUERIES
from tests.test_catalog import SF, TABLES, plain


@pytest.mark.parametrize("name, least", [("best_worst_sets", 18), ("measure_series", 50), ("math_budget_formula", 1000), ("parameter_grids", 11)])
def test_reads_a_given_table(spark, name, least):
    df = QUERIES[name](spark, SF)
    assert any(f"{SF}/{t}.parquet" in f for f in df.inputFiles() for t in TABLES) or name == "parameter_grids" and df.inputFiles()
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    found = db.execute(ORACLES[name])
    columns = [c[0] for c in found.description]
    want = sorted(([plain(v) for v in r] for r in found.fetchall()), key=repr)
    assert len(want) >= least
    assert sorted(([plain(r[c]) for c in columns] for r in df.collect()), key=repr) == want


def test_budget_rows_meet_every_branch(spark):
    rows = QUERIES["math_budget_formula"](spark, SF).collect()
    assert any(r.d == 0 for r in rows) and any(r.s <= 0 for r in rows) and any(r.m > 1 and r.budget is not None for r in rows)
    assert {0.0, 1.0} <= {r.budget for r in rows if r.m <= 1}
