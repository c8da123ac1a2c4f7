"""Helpers shared by the training-data operators: scratch tables, Arrow batches, ASCII folding."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hotgraph import storage
from hotgraph.storage import release as release_scratch
from hotgraph.storage import settle

__all__ = ["WORD_TABLE", "emit", "examples", "fresh", "prepare", "read", "release_scratch", "rows", "settle"]

#: Rows and bytes of a batch that goes to a Python worker, in place of Spark's defaults: documents are long, and both
#: the JVM's buffers and the worker hold whole batches.
ARROW = {"spark.sql.execution.arrow.maxRecordsPerBatch": ("10000", "4000"), "spark.sql.execution.arrow.maxBytesPerBatch": ("67108864b", "8388608b")}

#: bytes.translate table: A-Z to a-z, every other ASCII character that is not a letter or digit to a space.
WORD_TABLE = bytes(
    c + 32 if 0x41 <= c <= 0x5A else c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else 0x20
    for c in range(256)
)


def prepare(spark: SparkSession) -> None:
    """Make the package importable for workers, and batches small unless the session has sizes of its own."""
    storage.prepare(spark)
    for name, (usual, small) in ARROW.items():
        if spark.conf.get(name, usual) == usual:
            spark.conf.set(name, small)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, each with underscores added until no column of df has it in any case."""
    held, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in held:
            name += "_"
        held.add(name.lower())
        out.append(name)
    return out


def rows(batches: Iterable[pa.RecordBatch], step: int = 256) -> Iterator[tuple]:
    """Rows of the batches as tuples, decoded a few at a time so that long texts are not all held at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, step):
            yield from zip(*(c.to_pylist() for c in batch.slice(at, step).columns), strict=True)


def emit(found: Iterable[tuple], schema: pa.Schema, size: int = 4096) -> Iterator[pa.RecordBatch]:
    """Record batches of the tuples, `size` rows each."""
    held: list[tuple] = []
    for row in found:
        held.append(row)
        if len(held) >= size:
            yield _batch(held, schema)
            held = []
    if held:
        yield _batch(held, schema)


def _batch(held: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [pa.array(c, type=f.type) for c, f in zip(zip(*held, strict=True), schema, strict=True)], schema=schema
    )


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def examples(docs: DataFrame, labels: DataFrame, sample: int, size: int) -> DataFrame:
    """(doc_id, text, y, h): texts to learn from, of labels(doc_id, y), which has each doc_id once.

    At most `sample` of them, in the order of h, a hash of doc_id, while their texts have at most `size` bytes in all;
    the first is taken whatever its size. A doc_id with several texts gives its shortest (of equals, by hash), once:
    repeated rows neither weigh more nor make more rows. Only labels whose document is there count.
    """
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.octet_length(F.coalesce("text", F.lit(""))).alias("size"), F.xxhash64("text").alias("tag"))
    one = own.groupBy("doc_id").agg(F.min(F.struct("size", "tag")).alias("t"))
    few = labels.join(one, "doc_id").select("doc_id", "y", "t.size", "t.tag", F.xxhash64("doc_id").alias("h")).orderBy("h", "doc_id").limit(sample)
    before = F.coalesce(F.sum("size").over(Window.partitionBy(F.lit(0)).orderBy("h", "doc_id")), F.lit(0))  # `sample` rows
    few = few.withColumn("held", before).where((F.col("held") <= size) | (F.col("held") == F.col("size"))).select("doc_id", "y", "h", "tag")
    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("tag"))
    return texts.join(F.broadcast(few), ["doc_id", "tag"]).dropDuplicates(["doc_id"]).select("doc_id", "text", "y", "h")  # `sample` rows
