"""Near copies at a stated similarity against brute force over all pairs."""

import random

import pytest

pytest.importorskip("hotgraph.llm")

import numpy as np  # noqa: E402

from hotgraph.llm import widesimhash as w  # noqa: E402
from hotgraph.llm.simhash import keep_first, shingle_hashes  # noqa: E402


def corpus():
    r = random.Random(5)
    vocabulary = [f"w{k}" for k in range(3000)]
    passage = " ".join(r.choices(vocabulary, k=60))
    texts = []
    for base in range(30):
        words = r.choices(vocabulary, k=r.choice([80, 300, 900]))
        for copy in range(5):
            new = list(words)
            for _ in range(copy * len(words) // 200):
                new[r.randrange(len(new))] = r.choice(vocabulary)
            texts.append(" ".join(new) + (f" {passage}" if base % 3 == 0 else ""))
    return [*texts, texts[0], None, "", "one two"]


def brute(texts, least):
    sets = [set(np.unique(shingle_hashes(t, 5)).tolist()) for t in texts]
    return {(i, j) for i in range(len(sets)) for j in range(i) if sets[i] | sets[j] and len(sets[i] & sets[j]) >= least * len(sets[i] | sets[j])}


@pytest.mark.parametrize("cap", [4096, 10])
def test_similar(spark, cap):
    texts = corpus()
    docs = spark.createDataFrame([(k, t, "x", "y") for k, t in enumerate(texts)], "doc_id bigint, text string, group string, fp string").repartition(4)
    group = {r.doc_id: r.group for r in w.similar(docs, cap=cap).collect()}
    sure, none = brute(texts, 0.83), brute(texts, 0.7)
    assert all(group[i] == group[j] for i, j in sure)
    linked = {(i, j) for i in range(len(texts)) for j in range(i) if group[i] == group[j]}
    assert all(i // 5 == j // 5 or (i, j) in none or {i, j} == {0, 150} or {i, j} <= {0, 1, 2, 3, 4, 150} or not texts[i] and not texts[j] for i, j in linked)
    kept = {r.doc_id for r in keep_first(docs, w.similar(docs, cap=cap)).collect()}
    assert kept == {min(k for k in group if group[k] == g) for g in set(group.values())}


def test_forest():
    r = np.random.default_rng(1)
    base = r.integers(0, 2**63, (20, 4)).astype(np.uint64)
    prints = np.concatenate([base ^ (np.uint64(1) << r.integers(0, 63, (20, 4)).astype(np.uint64)) for _ in range(6)])
    up = list(range(len(prints)))

    def root(k):
        while up[k] != k:
            k = up[k]
        return k

    for a, b in w.forest(prints, 8):
        assert int(np.bitwise_count(prints[a] ^ prints[b]).sum()) <= 8
        up[max(root(a), root(b))] = min(root(a), root(b))
    for a in range(len(prints)):
        for b in range(a):
            assert (root(a) == root(b)) or int(np.bitwise_count(prints[a] ^ prints[b]).sum()) > 8


def test_links_are_exact_at_the_similarity_itself(spark):
    """Short and unequal texts: pairs at 0.8 are linked, pairs just below are not."""
    r = random.Random(8)
    texts, want = [], []
    for words, less in [(9, 1), (8, 1), (19, 3), (19, 4), (104, 20), (104, 21), (404, 80), (404, 82)]:
        for _ in range(8):
            whole = [f"v{r.randrange(10**9)}" for _ in range(words)]
            texts += [" ".join(whole), " ".join(whole[: words - less])]
            want.append((words - 4 - less) / (words - 4) >= 0.8)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(4)
    for cap in (4096, 10):
        group = {x.doc_id: x.group for x in w.similar(docs, cap=cap).collect()}
        assert [group[2 * k] == group[2 * k + 1] for k in range(len(want))] == want
        assert len(set(group.values())) == len(texts) - sum(want)


@pytest.mark.parametrize("cap", [4096, 3])
@pytest.mark.parametrize("similarity", [None, 0.8])
def test_nodes_whose_only_common_key_is_a_hot_one_meet(spark, cap, similarity):
    """Whatever a cell's size, every pair in it that the radius and the sizes allow is compared."""
    rows = [(k, bytes(127) + bytes([1 << k]), [7, 1000 + k], 100 + 4 * k) for k in range(6)] + [(9, bytes([255] * 128), [7], 100), (10, bytes(128), [8], 100)]
    nodes = spark.createDataFrame(rows, "node bigint, fp binary, keys array<bigint>, size bigint")
    up = {k: k for k, *_ in rows}

    def root(k):
        while up[k] != k:
            k = up[k]
        return k

    for r in w.links(nodes, 2, cap, similarity).collect():
        up[max(root(r.a), root(r.b))] = min(root(r.a), root(r.b))
    assert {k: root(k) for k in up} == dict.fromkeys(range(6), 0) | {9: 9, 10: 10}


def test_recall_over_all_pairs_and_nothing_below(spark):
    """The given documents: exact similarity of all pairs of five-word shingle sets against the groups."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    sets = {k: frozenset(shingle_hashes(t, 5).tolist()) for k, t in texts.items()}
    holds = {}
    for k, s in sets.items():
        for h in s:
            holds.setdefault(h, []).append(k)
    up = {k: k for k in sets}

    def root(k):
        while up[k] != k:
            k = up[k]
        return k

    pairs = 0
    for k, s in sets.items():
        common = {}
        for h in s:
            for j in holds[h]:
                if j < k:
                    common[j] = common.get(j, 0) + 1
        for j, n in common.items():
            if n >= 0.8 * (len(s) + len(sets[j]) - n) - 1e-9:
                pairs += 1
                up[max(root(k), root(j))] = min(root(k), root(j))
    empty = [k for k, s in sets.items() if not s]
    for k in empty:
        up[root(k)] = root(empty[0])
    group = {r.doc_id: r.group for r in w.similar(docs).collect()}
    members = {}
    for k in sets:
        members.setdefault(root(k), set()).add(k)
    found = {}
    for k, g in group.items():
        found.setdefault(g, set()).add(k)
    assert pairs > 50
    assert sorted(map(sorted, found.values())) == sorted(map(sorted, members.values()))
