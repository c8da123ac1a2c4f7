"""The two learners against plain loops, and samples that repeated rows do not enlarge."""

import math
import random
import time

import pytest

pytest.importorskip("hotgraph.llm")

import numpy as np  # noqa: E402

from hotgraph.llm import quality, toxicity  # noqa: E402
from hotgraph.llm.common import examples  # noqa: E402


def bags(n, places, seed):
    r = random.Random(seed)
    return [(np.array(sorted(r.sample(range(places), r.randrange(1, 9)))), r.random()) for _ in range(n)]


def test_ftrl_against_a_plain_loop():
    p = toxicity.Ftrl(bits=6, l1=0.3, l2=0.5, epochs=3)
    rows = [(at, int(x < 0.4 + 0.5 * (7 in at) - 0.3 * (9 in at))) for at, x in bags(200, 64, 1)]
    z, n, bz, bn, bias = [0.0] * 64, [0.0] * 64, 0.0, 0.0, 0.0

    def weight(i):
        if abs(z[i]) <= p.l1:
            return 0.0
        return -(z[i] - math.copysign(p.l1, z[i])) / ((p.beta + math.sqrt(n[i])) / p.alpha + p.l2)

    for _ in range(p.epochs):
        for at, y in rows:
            w = {i: weight(i) for i in at.tolist()}
            g = 1 / (1 + math.exp(-(bias + sum(w.values())))) - y
            for i in w:
                z[i] += g - (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / p.alpha * w[i]
                n[i] += g * g
            bz += g - (math.sqrt(bn + g * g) - math.sqrt(bn)) / p.alpha * bias
            bn += g * g
            bias = -bz / ((p.beta + math.sqrt(bn)) / p.alpha)
    got_bias, got = toxicity.fit(rows, p)
    want = {i: weight(i) for i in range(64) if weight(i)}
    assert got_bias == pytest.approx(bias) and got == pytest.approx(want) and 0 < len(want) < 64


def test_cumulative_link_gradient_and_order():
    """The steps lower the negative log-likelihood that a plain loop computes, and thresholds stay in order."""
    p = quality.Ordinal(bits=6, epochs=6, l2=0.0)
    names = [-1.5, 0.0, 0.25, 7.0]
    rows = []
    for at, x in bags(400, 64, 2):
        k = min(3, int(x * 2 + 1.5 * (5 in at) + 0.8 * (11 in at)))
        rows.append((at, np.full(len(at), 0.5, np.float32), names[k]))

    def loss(m):
        total = 0.0
        for at, v, y in rows:
            f = sum(m.weights.get(int(i), 0.0) * float(x) for i, x in zip(at, v, strict=True))
            tail = [1.0, *(1 / (1 + math.exp(-(f - t))) for t in m.theta), 0.0]
            k = names.index(y)
            total -= math.log(max(tail[k] - tail[k + 1], 1e-12))
        return total / len(rows)

    none, fitted = quality.fit(rows, quality.Ordinal(bits=6, epochs=0)), quality.fit(rows, p)
    assert fitted.ratings == names and fitted.theta == sorted(fitted.theta)
    assert loss(fitted) < loss(none) - 0.1


def test_cumulative_link_against_a_plain_loop():
    """AdaGrad steps along numeric derivatives of the negative log-likelihood."""
    p = quality.Ordinal(bits=5, epochs=2, l2=0.0)
    rows = [(at, np.full(len(at), 0.5, np.float32), min(2, int(x * 3))) for at, x in bags(40, 32, 3)]
    w, g2, f2 = [0.0] * 32, [1e-3] * 32, [1e-3] * 2
    share = [sum(y > k for *_, y in rows) / len(rows) for k in range(2)]
    cut = [-math.log((s + 1e-3) / (1 - s + 1e-3)) for s in share]
    free = [cut[0], math.log(max(cut[1] - cut[0], 1e-3))]

    def cost(f, own, y):
        theta = [own[0], own[0] + math.exp(own[1])]
        tail = [1.0, *(1 / (1 + math.exp(t - f)) for t in theta), 0.0]
        return -math.log(tail[y] - tail[y + 1])

    e = 1e-6
    for _ in range(p.epochs):
        for at, v, y in rows:
            f = sum(w[i] * float(x) for i, x in zip(at.tolist(), v, strict=True))
            slope = (cost(f + e, free, y) - cost(f - e, free, y)) / (2 * e)
            own = [(cost(f, [x + e * (j == k) for j, x in enumerate(free)], y) - cost(f, [x - e * (j == k) for j, x in enumerate(free)], y)) / (2 * e) for k in range(2)]
            for i, x in zip(at.tolist(), v, strict=True):
                d = slope * float(x)
                g2[i] += d * d
                w[i] -= p.rate * d / math.sqrt(g2[i])
            for k in range(2):
                f2[k] += own[k] ** 2
                free[k] -= 0.05 * own[k] / math.sqrt(f2[k])
    got = quality.fit(rows, p)
    assert got.theta == pytest.approx([free[0], free[0] + math.exp(free[1])], rel=1e-3)
    assert [got.weights.get(i, 0.0) for i in range(32)] == pytest.approx(w, rel=1e-3, abs=1e-4)


def test_ratings_are_ranks_whatever_their_numbers(spark):
    docs = spark.createDataFrame([(k, ("calm words here " if k % 2 else "NOW!!! $$$ ### ") * 5) for k in range(60)] + [(60, "x " * 200_000)], "doc_id bigint, text string")
    low, high = -0.5, 2_000_000.0
    labels = spark.createDataFrame([(k, high if k % 2 else low) for k in range(60)] + [(60, float("nan")), (61, 1.0)], "doc_id bigint, quality double")
    began = time.time()
    model = quality.train(docs, labels)
    assert model.ratings == [low, high] and len(model.theta) == 1 and time.time() - began < 60
    got = {r.doc_id: r for r in quality.grade(docs, model).collect()}
    assert all((got[k].tail > 0.5) == bool(k % 2) and low <= got[k].expected_grade <= high for k in range(60))
    assert {r.tail for r in quality.grade(docs, model, above=-1).collect()} == {1.0}
    assert {r.tail for r in quality.grade(docs, model, above=high).collect()} == {0.0}
    assert quality.graded(docs.limit(0), labels).count() == 0


def test_repeated_rows_enter_the_sample_once(spark):
    docs = spark.createDataFrame([(1, "same")] * 40_000 + [(2, "two"), (2, "a longer text"), (3, None), (4, "y" * 5000)], "doc_id bigint, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(1, 7)], "doc_id bigint, y int")
    got = sorted((r.doc_id, r.text) for r in examples(docs, labels, 100, 10**6).collect())
    assert got == [(1, "same"), (2, "two"), (3, None), (4, "y" * 5000)]
    order = [r.doc_id for r in examples(docs, labels, 100, 10**6).orderBy("h", "doc_id").collect()]
    few = {r.doc_id for r in examples(docs, labels, 2, 10**6).collect()}
    assert few == set(order[:2])
    sizes, held, want = {1: 4, 2: 3, 3: 0, 4: 5000}, 0, []
    for k in order:
        held += sizes[k]
        if held <= 10 or held == sizes[k]:
            want.append(k)
    assert {r.doc_id for r in examples(docs, labels, 100, 10).collect()} == set(want)
