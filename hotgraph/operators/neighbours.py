"""Nearest neighbours by cosine, exactly, by blocks."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hotgraph.storage import prepare

#: Bytes of a block's vectors at most.
_BYTES = 8 << 20
_OUT = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("cosine", pa.float64())])


def _best(own: np.ndarray, other: np.ndarray, c: np.ndarray, k: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each of own the k best of the others by c, ties by id."""
    for n, ident in enumerate(own):
        good = np.flatnonzero(np.isfinite(c[n]) & (other != ident))
        best = good[np.lexsort((other[good], -c[n][good]))[:k]]
        yield np.full(len(best), ident), other[best], c[n][best]


def nearest(vectors: DataFrame, k: int, block: int = 2048) -> DataFrame:
    """(src, dst, cosine): the k nearest other vectors of each, ties by id; cosines count to 9 digits.

    Vectors are dealt to blocks of at most `block` rows and 8 MB. A cell holds two blocks, or one alone, and answers for
    both: every pair is multiplied once, and a vector is sent once to each block. The work is that of all pairs, as exact
    neighbours need. Null and zero vectors have no neighbours.
    """
    prepare(vectors.sparkSession)
    held = vectors.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v")).where("v is not null")
    shape = held.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("width")).first()
    blocks = max(1, -(-shape.n // max(1, min(block, _BYTES // (8 * max(1, shape.width or 1))))))
    mine = F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("m")
    every = F.sequence(F.lit(0).cast("bigint"), F.lit(blocks - 1).cast("bigint"))
    sent = held.select(mine, F.explode(every).alias("o"), "id", "v")
    cells = sent.select(F.least("m", "o").alias("i"), F.greatest("m", "o").alias("j"), "m", "id", "v")
    dealt = cells.repartition("i", "j").sortWithinPartitions("i", "j", "m", "id")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, sides = None, {}

        def done() -> Iterator[pa.RecordBatch]:
            if last is None or len(sides) < len(set(last)):
                return
            ids = [np.array([r[0] for r in side], np.int64) for side in sides.values()]
            x = [np.array([r[1] for r in side], float) for side in sides.values()]
            norm = [np.linalg.norm(m, axis=1) for m in x]
            with np.errstate(all="ignore"):
                c = np.round((x[0] @ x[-1].T) / np.outer(norm[0], norm[-1]), 9)
            found = [*_best(ids[0], ids[-1], c, k), *(_best(ids[1], ids[0], c.T, k) if len(ids) > 1 else ())]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(column)) for column in zip(*found, strict=True)], schema=_OUT)

        for batch in batches:
            for i, j, m, ident, v in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (i, j) != last:
                    yield from done()
                    last, sides = (i, j), {}
                sides.setdefault(m, []).append((ident, v))
        yield from done()

    best = dealt.mapInArrow(run, "src bigint, dst bigint, cosine double")
    by = Window.partitionBy("src").orderBy(F.col("cosine").desc(), "dst")
    return best.withColumn("k", F.row_number().over(by)).where(F.col("k") <= k).select("src", "dst", "cosine")
