"""Streams whose results are as large as their inputs."""

from pyspark.sql import functions as F

from hotgraph.catalog import QUERIES
from hotgraph.streaming import windows


def test_sessions_come_from_a_written_table(spark, tmp_path):
    """Sessions are nearly as many as events: the driver holds none, and later batches replace what was written."""
    rows = [(k, f"2024-01-0{1 + k // 4} 00:{10 * (k % 4)}:00", k % 2, "view", 1.0, None) for k in range(8)]
    e = spark.createDataFrame(rows, "event_id bigint, ts string, user_id bigint, event_type string, value double, props string").withColumn("ts", F.to_timestamp_ntz("ts"))
    e.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = QUERIES["st_session"](spark, str(tmp_path))
    assert got.inputFiles() and all(name.endswith(".parquet") for name in got.inputFiles())
    assert sorted((str(r.window_start), str(r.window_end), r.user_id, r.n) for r in got.collect()) == [
        (f"2024-01-0{d} 00:{m}:00", f"2024-01-0{d} {end}:00", u, 2) for d in (1, 2) for u, m, end in ((0, "00", "00:50"), (1, "10", "01:00"))
    ]
    path = tmp_path / "parts"
    for day in (1, 2):
        e.where(F.dayofmonth("ts") == day).coalesce(1).write.mode("append").parquet(str(path))
    twice = windows.replaced(windows.sessions(windows.read_events(spark, str(path), 1)))
    assert twice.count() == 4 and len({name.rsplit("/", 2)[-2] for name in twice.inputFiles()}) == 1
    assert not windows.replaced(windows.sessions(windows.read_events(spark, str(path), 1).where("event_id < 0"))).count()
