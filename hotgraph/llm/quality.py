"""Quality classifier: ordinal cumulative-link regression with weights shared by all thresholds.

Grades are the distinct ratings in order, whatever numbers they are (negative and fractional ones included), K of them.
One weight vector over hashed text features gives a value f; K - 1 ordered thresholds give P(rating > grade k) =
sigmoid(f - threshold k). The expected rating is the smallest and, for each step to the next, its width times its tail;
the tail above the chosen rating selects. Thresholds stay in order, as each is the one before plus exp of a free number.
Features are hashed: word shapes (letters to a, A-Z to A, digits to 0, runs shortened), their pairs, runs of other
characters, and bands of the shares of capitals, digits, symbols and repeated lines, of the length and of word length.
Fitting goes over a bounded sample of rated documents (`sample` of them and `size` bytes of text, by hash of doc_id; a
doc_id that has several rows counts once) in one task, by AdaGrad steps on the log-likelihood; the weights, at most
2^bits, and the thresholds, fewer than `sample`, are broadcast to grade every whole text.

A null text is empty. Ratings that are null or not finite are not used; a doc_id rated twice takes its smallest rating.
Without two grades to learn from, the tail is 1 for every document, so all are kept. Only doc_id, text and the rating are read.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, examples, prepare, rows
from hotgraph.llm.toxicity import held_out


@dataclass(frozen=True)
class Ordinal:
    bits: int = 18
    rate: float = 0.3
    l2: float = 1e-5
    epochs: int = 4
    sample: int = 8000
    size: int = 256 << 20


@dataclass(frozen=True)
class Model:
    """ratings in order, a threshold between each two, and the weights that are not zero; none without two ratings."""

    ratings: list[float]
    theta: list[float]
    weights: dict[int, float]


_SHAPES = bytes(
    0x61 if 0x61 <= c <= 0x7A or c >= 0x80 else 0x41 if 0x41 <= c <= 0x5A else 0x30 if 0x30 <= c <= 0x39 else c for c in range(256)
)
_RUNS = re.compile(rb"(.)\1{2,}", re.S)


def _band(x: float) -> int:
    return min(20, int(x * 20))


def features(text: str | None, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and values of the text's features; values are square roots of frequencies, with norm 1, and 1 for bands."""
    raw = (text or "").encode()
    shapes = _RUNS.sub(rb"\1\1", raw.translate(_SHAPES)).split()
    lines = (text or "").split("\n")
    n = max(1, len(raw))
    count = np.bincount(np.frombuffer(raw.translate(_SHAPES), np.uint8), minlength=128) if raw else np.zeros(128)
    space = count[0x20] + count[0x0A]
    bands = [
        ("caps", _band(count[0x41] / n)), ("digits", _band(count[0x30] / n)),
        ("marks", _band((n - count[0x41] - count[0x30] - count[0x61] - space) / n)),
        ("again", _band(1 - len(set(lines)) / len(lines))), ("length", len(raw).bit_length()),
        ("word", min(30, len(raw) // max(1, len(shapes)))), ("lines", len(lines).bit_length()),
        ("distinct", _band(len(set((text or "").split())) / max(1, len(shapes)))),
    ]
    crc = np.fromiter(map(zlib.crc32, shapes), np.uint64, len(shapes)) + np.uint64(1)
    both = np.concatenate([crc, crc[:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + crc[1:]]) if len(crc) else crc
    at, often = np.unique((both * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - bits), return_counts=True)
    value = np.sqrt(often)
    value = value / np.linalg.norm(value) if len(value) else value
    own = [(zlib.crc32(f"{k}={v}".encode()) * 0x9E3779B1 & 0xFFFFFFFF) >> (32 - bits) for k, v in bands]
    return np.concatenate([at.astype(np.int64), np.array(own, np.int64)]), np.concatenate([value, np.full(len(own), 0.5)])


def _sigmoid(x: np.ndarray | float) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


def fit(rated: list[tuple[np.ndarray, np.ndarray, float]], p: Ordinal) -> Model:
    """The model of (places, values, rating) of each example, in their order."""
    ratings = sorted({y for *_, y in rated})
    grades, rank = len(ratings), {y: k for k, y in enumerate(ratings)}
    if grades < 2:
        return Model(ratings, [], {})
    examples = [(at, value, rank[y]) for at, value, y in rated]
    w, g2 = np.zeros(1 << p.bits), np.full(1 << p.bits, 1e-3)
    free, f2 = np.zeros(grades - 1), np.full(grades - 1, 1e-3)
    share = 1 - np.cumsum(np.bincount([y for *_, y in examples], minlength=grades))[:-1] / len(examples)
    cut = [-math.log((s + 1e-3) / (1 - s + 1e-3)) for s in share]
    free[0] = cut[0]
    free[1:] = np.log(np.maximum(np.diff(cut), 1e-3))
    for _ in range(p.epochs):
        for at, value, y in examples:
            theta = np.cumsum(np.concatenate([free[:1], np.exp(free[1:])]))
            tail = np.concatenate([[1.0], _sigmoid(float(w[at] @ value) - theta), [0.0]])
            slope = tail * (1 - tail)
            here = max(tail[y] - tail[y + 1], 1e-9)
            d_f = -(slope[y] - slope[y + 1]) / here
            d_theta = np.zeros(grades - 1)
            if y:
                d_theta[y - 1] += slope[y] / here
            if y < grades - 1:
                d_theta[y] -= slope[y + 1] / here
            d_free = np.cumsum(d_theta[::-1])[::-1] * np.concatenate([[1.0], np.exp(free[1:])])
            d_w = d_f * value + p.l2 * w[at]
            g2[at] += d_w**2
            w[at] -= p.rate * d_w / np.sqrt(g2[at])
            f2 += d_free**2
            free -= 0.05 * d_free / np.sqrt(f2)
    theta = np.cumsum(np.concatenate([free[:1], np.exp(free[1:])]))
    kept = np.flatnonzero(w)
    return Model(ratings, theta.tolist(), dict(zip(kept.tolist(), w[kept].tolist(), strict=True)))


def train(docs: DataFrame, labels: DataFrame, rating: str = "quality", p: Ordinal = Ordinal()) -> Model:
    """Fit on the sample of rated rows outside the held-out fifth."""
    prepare(docs.sparkSession)
    ids = labels.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col(rating).cast("double").alias("y"))
    ids = ids.where((F.abs("y") < float("inf")) & ~held_out()).groupBy("doc_id").agg(F.min("y").alias("y"))
    seen = pa.schema([("h", pa.int64()), ("doc_id", pa.int64()), ("y", pa.float64()), ("at", pa.binary()), ("v", pa.binary())])
    out = pa.schema([("at", pa.int64()), ("w", pa.float64())])

    def featurise(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def each() -> Iterator[tuple]:
            for d, t, y, h in rows(batches):
                at, v = features(t, p.bits)
                yield h, d, y, at.astype("<i4").tobytes(), v.astype("<f4").tobytes()

        yield from emit(each(), seen, 512)

    def learn(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = fit([(np.frombuffer(at, "<i4"), np.frombuffer(v, "<f4"), y) for *_, y, at, v in rows(batches)], p)
        below = [*((-1 - 2 * k, x) for k, x in enumerate(m.ratings)), *((-2 - 2 * k, x) for k, x in enumerate(m.theta))]
        yield from emit([*below, *m.weights.items()], out)

    bagged = examples(docs, ids, p.sample, p.size).mapInArrow(featurise, "h bigint, doc_id bigint, y double, at binary, v binary")
    learnt = bagged.repartition(1).sortWithinPartitions("h", "doc_id", "at").mapInArrow(learn, "at bigint, w double")
    got = sorted(((r.at, r.w) for r in learnt.collect()), reverse=True)
    pick = lambda odd: [w for at, w in got if at < 0 and at % 2 == odd]
    return Model(pick(1), pick(0), {at: w for at, w in got if at >= 0})


def grade(docs: DataFrame, model: Model, p: Ordinal = Ordinal(), above: float = 0) -> DataFrame:
    """(doc_id, expected_grade, tail) for each document; tail = P(rating > above)."""
    prepare(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast((model.ratings, model.theta, model.weights))
    schema = pa.schema([("doc_id", pa.int64()), ("expected_grade", pa.float64()), ("tail", pa.float64())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ratings, theta, sparse = held.value
        w = np.zeros(1 << p.bits)
        w[list(sparse)] = list(sparse.values())
        step, at_most = np.diff(ratings), int(np.searchsorted(ratings, above, side="right"))

        def each() -> Iterator[tuple]:
            for doc, text in rows(batches):
                if not theta:
                    yield doc, None, 1.0
                    continue
                at, v = features(text, p.bits)
                tail = _sigmoid(float(w[at] @ v) - np.array(theta))
                over = 1.0 if at_most == 0 else 0.0 if at_most > len(tail) else float(tail[at_most - 1])
                yield doc, float(ratings[0] + step @ tail), over

        yield from emit(each(), schema)

    picked = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    return picked.mapInArrow(run, "doc_id bigint, expected_grade double, tail double")


def graded(docs: DataFrame, labels: DataFrame, p: Ordinal = Ordinal()) -> DataFrame:
    """doc_id, held_out, expected_grade, tail, kept (tail >= 0.5) for each document."""
    found = grade(docs, train(docs, labels, p=p), p)
    return found.select("doc_id", held_out().alias("held_out"), "expected_grade", "tail", (F.col("tail") >= 0.5).alias("kept"))
