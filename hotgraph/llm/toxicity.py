"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Words are runs of letters, digits and non-ASCII characters with A-Z lower-cased. Features are words, their stems (first
five bytes), adjacent pairs, and pairs that skip one or two words, hashed to 2^bits places; a feature counts once a document. Training
goes over a bounded sample of labelled documents (`sample` of them and `size` bytes of text, by hash of doc_id, so it is
the same on every run; a doc_id that has several rows counts once): their features are made on the executors, and one task runs the per-coordinate updates. The L1 term leaves few weights
that are not zero; only these are collected (at most 2^bits) and broadcast to score every whole text.

A null text is empty; it is scored from the bias. Labels that are null are not used, and a doc_id labelled twice
counts as toxic if any of its rows says so. Without any label every score is the prior, 0.1. Rows with a null
doc_id are never learnt from. Only doc_id, text and toxic are read. Repeated rows are scored each.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, examples, prepare, rows
from hotgraph.llm.decontaminate import normal_words


@dataclass(frozen=True)
class Ftrl:
    """alpha, beta: the learning rate's scale and offset; l1, l2: regularisation; sample, size: documents learnt from, at
    most, and bytes of their texts in all.
    """

    bits: int = 20
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 8.0
    l2: float = 1.0
    epochs: int = 5
    sample: int = 8000
    size: int = 256 << 20


#: Bytes of a word that count as its stem.
STEM = 5
#: Odd multipliers that mix word hashes: one for each of word, pair, pair over one word, pair over two.
_MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93], np.uint64)


def features(text: str | None, bits: int) -> np.ndarray:
    """Places of the text's features, sorted, each once."""
    return np.unique(_places(text, bits))


def _places(text: str | None, bits: int) -> np.ndarray:
    words = normal_words(text)
    if not words:
        return np.empty(0, np.int64)
    h = np.fromiter(map(zlib.crc32, words), np.uint64, len(words)) + np.uint64(1)
    stem = np.fromiter((zlib.crc32(w[:STEM], 7) for w in words), np.uint64, len(words)) + np.uint64(1)
    mixed = [h, stem * _MIX[1], *(h[:-k] * _MIX[k] + h[k:] for k in (1, 2, 3) if len(h) > k)]
    return ((np.concatenate(mixed) * _MIX[0]) >> np.uint64(64 - bits)).astype(np.int64)


def fit(examples: list[tuple[np.ndarray, int]], p: Ftrl) -> tuple[float, dict[int, float]]:
    """Bias and the weights that are not zero. The bias is a coordinate without L1."""
    toxic = sum(y for _, y in examples)
    if not 0 < toxic < len(examples):
        rate = (toxic + 0.1) / (len(examples) + 1)
        return math.log(rate / (1 - rate)), {}
    z, n = np.zeros(1 << p.bits), np.zeros(1 << p.bits)
    bz, bn, bias = 0.0, 0.0, 0.0

    def weights(at: np.ndarray | slice) -> np.ndarray:
        zi = z[at]
        return np.where(np.abs(zi) <= p.l1, 0.0, -(zi - np.sign(zi) * p.l1) / ((p.beta + np.sqrt(n[at])) / p.alpha + p.l2))

    for _ in range(p.epochs):
        for at, y in examples:
            w = weights(at)
            g = 1 / (1 + math.exp(-max(-35.0, min(35.0, bias + float(w.sum()))))) - y
            rate = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / p.alpha
            z[at] += g - rate * w
            n[at] += g * g
            bz += g - (math.sqrt(bn + g * g) - math.sqrt(bn)) / p.alpha * bias
            bn += g * g
            bias = -bz / ((p.beta + math.sqrt(bn)) / p.alpha)
    w = weights(slice(None))
    kept = np.flatnonzero(w)
    return bias, dict(zip(kept.tolist(), w[kept].tolist(), strict=True))


def held_out() -> F.Column:
    """True where crc32 of doc_id as text leaves 0 modulo 5, and for null ids: such rows are never learnt from."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(True))


def train(docs: DataFrame, labels: DataFrame, p: Ftrl = Ftrl()) -> tuple[float, dict[int, float]]:
    """Fit on up to p.sample labelled rows outside the held-out fifth."""
    prepare(docs.sparkSession)
    ids = labels.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("toxic").cast("int").alias("y"))
    ids = ids.where(F.col("y").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("y").alias("y"))
    seen = pa.schema([("h", pa.int64()), ("doc_id", pa.int64()), ("y", pa.int32()), ("at", pa.binary())])
    out = pa.schema([("at", pa.int64()), ("w", pa.float64())])

    def featurise(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = ((h, d, y, features(t, p.bits).astype("<i4").tobytes()) for d, t, y, h in rows(batches))
        yield from emit(each, seen, 512)

    def learn(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bias, w = fit([(np.frombuffer(at, "<i4"), y) for _, _, y, at in rows(batches)], p)
        yield from emit([(-1, bias), *w.items()], out)

    bagged = examples(docs, ids, p.sample, p.size).mapInArrow(featurise, "h bigint, doc_id bigint, y int, at binary")
    learnt = bagged.repartition(1).sortWithinPartitions("h", "doc_id", "at").mapInArrow(learn, "at bigint, w double")
    got = {r.at: r.w for r in learnt.collect()}
    if not got:
        return fit([], p)
    return got.pop(-1), got


def score(docs: DataFrame, model: tuple[float, dict[int, float]], p: Ftrl = Ftrl()) -> DataFrame:
    """(doc_id, score) for each document."""
    prepare(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = scorer(held.value, p)
        yield from emit(((doc, of(text)) for doc, text in rows(batches)), schema)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(run, "doc_id bigint, score double")


def keep_clean(docs: DataFrame, model: tuple[float, dict[int, float]], p: Ftrl = Ftrl(), below: float = 0.5) -> DataFrame:
    """docs whose score is below the limit, with all their columns."""
    prepare(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        of = scorer(held.value, p)
        for texts in batches:
            yield pd.Series([of(t) < below for t in texts], dtype=bool)

    run.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return docs.where(F.pandas_udf(run, "boolean")("text"))


def scorer(model: tuple[float, dict[int, float]], p: Ftrl):  # noqa: ANN201
    """Function from a text to its score."""
    bias, sparse = model
    w = np.zeros(1 << p.bits, np.float32)
    w[list(sparse)] = list(sparse.values())
    known = w != 0

    def of(text: str | None) -> float:
        total = bias
        if sparse:
            at = _places(text, p.bits)
            at = np.unique(at[known[at]])
            total += float(w[at].astype(np.float64).sum())
        return 1 / (1 + math.exp(-max(-35.0, min(35.0, total))))

    return of


def verdicts(docs: DataFrame, labels: DataFrame, p: Ftrl = Ftrl()) -> DataFrame:
    """doc_id, held_out, score, predicted for each document."""
    scored = score(docs, train(docs, labels, p), p)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
