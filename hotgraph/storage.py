"""Tables in the folder that driver and executors share: lineage cuts, versions, size checks."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
_written: list[str] = []
_on_release: list[Callable[[], None]] = []

#: Rows up to which a frame that has been counted may be broadcast (two or three longs a row).
BROADCAST_ROWS = 5_000_000


def prepare(spark: SparkSession) -> None:
    """Let Python workers import this package where it is not installed on them but shares the path."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if _ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([*paths, _ROOT])


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where it is unset and the master is local."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="hotgraph-")
        spark.conf.set("spark.checkpoint.dir", root)
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df and read it again: cuts the lineage, survives lost executors, and gives the planner true sizes."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/hotgraph/{uuid.uuid4().hex}-{name}"
    df.write.parquet(path)
    _written.append(path)
    held = spark.read.schema(df.schema).parquet(path)
    held._settled = path
    return held


def counted(df: DataFrame) -> int:
    """Rows; of a frame that settle() wrote they are counted once."""
    if not hasattr(df, "_settled"):
        return df.count()
    if not hasattr(df, "_rows"):
        df._rows = df.count()
    return df._rows


def discard(*frames: DataFrame | None) -> None:
    """Delete tables that settle() wrote, whose last reader is done; other frames are left alone."""
    for df in frames:
        path = getattr(df, "_settled", None)
        if path in _written:
            _written.remove(path)
            delete(df.sparkSession, path)


@contextmanager
def cleared(spark: SparkSession) -> Iterator[list[DataFrame]]:
    """Delete on exit what settle() writes inside, but for the frames that are put into the list it gives."""
    before, kept = set(_written), []
    yield kept
    stay = before | {getattr(df, "_settled", None) for df in kept}
    for path in [p for p in _written if p not in stay]:
        _written.remove(path)
        delete(spark, path)


def on_release(forget: Callable[[], None]) -> None:
    """Have release() call this too: for whoever keeps frames that read settled tables."""
    _on_release.append(forget)


def delete(spark: SparkSession, path: str) -> bool:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return bool(at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True))


def pin(df: DataFrame, *keys: str) -> DataFrame:
    """df hash-partitioned by keys into as many partitions as shuffles have, with that layout known to the planner.

    Reliable checkpoints keep the partitioning, so a loop that joins on the keys does not shuffle df again.
    """
    spark = df.sparkSession
    shared_root(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(parts, *keys).checkpoint(eager=True)


def release(spark: SparkSession) -> int:
    """Delete what settle() wrote in this process; call it when the results that read it are written."""
    done = 0
    while _written:
        done += delete(spark, _written.pop())
    for forget in _on_release:
        forget()
    return done


def bounded(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """True when df (settled or cheap) has at most so many rows; reads no more than it must."""
    return df.limit(rows + 1).count() <= rows
