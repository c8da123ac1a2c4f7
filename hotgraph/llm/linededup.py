"""Line dedup: hashes range-partitioned with a secondary sort, first occurrences streamed, bitmaps returned.

A line's key is the line without white space at its ends, A-Z lower-cased. Keys of at least `least` code points
that at least two documents hold lose all their lines except in the smallest doc_id. Each such line becomes one
small row (128-bit hash of the key, document, position); the rows are range-partitioned on all of these, so even
a line that a third of all documents share is dealt over many partitions, and sorted inside each. A stream over a
partition knows the first document of every key that begins there. Only the key that a partition opens with may
have begun before: one summary row a partition settles these, and nothing else leaves the executors. What comes
back is a compressed keep bitmap for each document that loses lines; bits past its end are kept lines.

A null or empty text is one empty line. Rows with a null doc_id are kept whole and hold nothing for others. Rows
that repeat a doc_id count as that document: each loses its own lines by the same rule. Columns whose names clash
with the helper's are left alone: only doc_id and text are read and the others are passed through by the caller.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, fresh, prepare, rows, settle

#: The white space that is stripped, and the least length of a key in code points.
SPACE = " \t\n\x0b\x0c\r"
LEAST = 10
#: Rows to a partition of the sorted lines.
ROWS_A_PART = 2_000_000

_LINES = pa.schema([("h1", pa.int64()), ("h2", pa.int64()), ("doc", pa.int64()), ("tag", pa.int64()), ("pos", pa.int32())])
_MARKS = pa.schema([
    ("part", pa.int32()), ("kind", pa.string()), ("h1", pa.int64()), ("h2", pa.int64()), ("doc", pa.int64()),
    ("tag", pa.int64()), ("pos", pa.int32()),
])


def line_key(line: str) -> bytes:
    return line.strip(SPACE).encode().lower()


def _tagged(docs: DataFrame) -> DataFrame:
    """tag tells rows with the same doc_id and different texts apart."""
    return docs.select(F.col("doc_id").cast("bigint").alias("doc"), "text", F.xxhash64("text").alias("tag"))


def line_rows(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """(h1, h2, doc, tag, pos) for each line whose key is long enough."""
    prepare(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def each() -> Iterator[tuple]:
            digest, signed = xxhash.xxh3_128_digest, int.from_bytes
            for doc, text, tag in rows(batches):
                for pos, line in enumerate((text or "").split("\n")):
                    if len(line) >= least and len(key := line.strip(SPACE)) >= least:
                        h = digest(key.encode().lower())
                        yield signed(h[:8], "big", signed=True), signed(h[8:], "big", signed=True), doc, tag, pos

        yield from emit(each(), _LINES, 16384)

    return _tagged(docs).where("doc is not null").mapInArrow(run, "h1 bigint, h2 bigint, doc bigint, tag bigint, pos int")


def _stream(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple]:
    """Of one sorted partition: dropped lines, those of the opening key that wait for earlier partitions, a summary."""
    part, key, first, opening = TaskContext.get().partitionId(), None, None, True
    for h1, h2, doc, tag, pos in rows(batches, 8192):
        if (h1, h2) != key:
            opening = key is None
            key, first = (h1, h2), doc
        if doc != first:
            yield part, "drop", None, None, doc, tag, pos
        elif opening:
            yield part, "open", h1, h2, doc, tag, pos
    if key is not None:
        yield part, "last", *key, first, None, None


def dropped_lines(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """(doc, tag, pos) of every line that goes."""
    spark = docs.sparkSession
    lines = settle(line_rows(docs, least), "lines")
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")), -(-lines.count() // ROWS_A_PART))
    order = ["h1", "h2", "doc", "tag", "pos"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from emit(_stream(batches), _MARKS, 16384)

    dealt = lines.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    marks = settle(
        dealt.mapInArrow(run, "part int, kind string, h1 bigint, h2 bigint, doc bigint, tag bigint, pos int"), "marks"
    )
    # One row a partition: its last key and that key's first document in it; at most `parts` rows.
    lasts = sorted((r.part, (r.h1, r.h2), r.doc) for r in marks.where("kind = 'last'").select("part", "h1", "h2", "doc").collect())
    holder, earlier = None, []  # the key that earlier partitions ended with, and its first document
    for part, key, first in lasts:
        if holder is not None:
            earlier.append((part, *holder))
        holder = holder if holder is not None and holder[:2] == key else (*key, first)
    before = spark.createDataFrame(earlier, "part int, k1 bigint, k2 bigint, owner bigint")
    waiting = marks.where("kind = 'open'").join(F.broadcast(before), "part").where("h1 = k1 and h2 = k2 and doc > owner")
    return marks.where("kind = 'drop'").select("doc", "tag", "pos").union(waiting.select("doc", "tag", "pos"))


def keep_bitmaps(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """(doc, tag, n_dropped, keep) for each document that loses lines; keep is a zlib-compressed bitmap."""
    by_doc = dropped_lines(docs, least).groupBy("doc", "tag").agg(F.collect_set("pos").alias("pos"))
    schema = pa.schema([("doc", pa.int64()), ("tag", pa.int64()), ("n_dropped", pa.int64()), ("keep", pa.binary())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def each() -> Iterator[tuple]:
            for doc, tag, pos in rows(batches):
                keep = np.ones(max(pos) // 8 * 8 + 8, bool)
                keep[pos] = False
                yield doc, tag, len(pos), zlib.compress(np.packbits(keep).tobytes())

        yield from emit(each(), schema)

    return by_doc.mapInArrow(run, "doc bigint, tag bigint, n_dropped bigint, keep binary")


def _kept(text: str | None, keep: bytes | None) -> tuple[int, int, str]:
    """Lines before, lines dropped, and the text that stays."""
    lines = (text or "").split("\n")
    if keep is None:
        return len(lines), 0, text or ""
    bits = np.ones(len(lines), bool)
    held = np.unpackbits(np.frombuffer(zlib.decompress(keep), np.uint8))[: len(lines)].astype(bool)
    bits[: len(held)] = held
    return len(lines), int((~bits).sum()), "\n".join(x for x, b in zip(lines, bits, strict=True) if b)


def _joined(docs: DataFrame, bitmaps: DataFrame) -> tuple[DataFrame, str]:
    """docs with each row's bitmap in a new column, whose name comes too. Texts are never sorted, and bitmaps only
    broadcast when their files are small.
    """
    spark = docs.sparkSession
    limit = spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
    d, t, k = fresh(docs, "_doc", "_tag", "_keep")
    bitmaps = bitmaps.select(F.col("doc").alias(d), F.col("tag").alias(t), F.col("keep").alias(k))
    known = int(str(bitmaps._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    side = bitmaps if known <= limit else bitmaps.hint("shuffle_hash")
    on = (F.col("doc_id").cast("bigint") == F.col(d)) & (F.xxhash64("text") == F.col(t))
    return docs.join(side, on, "left").select(*docs.columns, k), k


def keep_report(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_sha256) for each document, by applying the bitmaps to the texts."""
    bitmaps = settle(keep_bitmaps(docs, least), "bitmaps")
    schema = pa.schema([("doc_id", pa.int64()), ("n_lines", pa.int64()), ("n_dropped", pa.int64()), ("kept_sha256", pa.string())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def each() -> Iterator[tuple]:
            for doc, text, keep in rows(batches):
                n, gone, kept = _kept(text, keep)
                yield doc, n, gone, hashlib.sha256(kept.encode()).hexdigest()

        yield from emit(each(), schema)

    joined, _ = _joined(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text"), bitmaps)
    return joined.mapInArrow(run, "doc_id bigint, n_lines bigint, n_dropped bigint, kept_sha256 string")


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame) -> DataFrame:
    """docs with text cut down to its kept lines; all other columns as they were. A null text stays null."""
    cut = F.pandas_udf(_cut, "string")
    joined, k = _joined(docs, bitmaps)
    text = F.when(F.col(k).isNull(), F.col("text")).otherwise(cut("text", k))
    return joined.withColumn("text", text).select(*docs.columns)


def _cut(text, keep):  # noqa: ANN001, ANN202
    import pandas as pd

    return pd.Series([t if k is None else _kept(t, k)[2] for t, k in zip(text, keep, strict=True)], dtype=object)
