"""SimHash for a stated similarity: 1,024-bit fingerprints over word shingles, BK-trees in cells named by shared shingles.

Fingerprints only choose candidates. For Jaccard similarity J the cosine is at least 2 J / (1 + J), and each bit
differs with probability angle / pi, or a little more in small sets, where the majority may tie. The radius holds all
pairs of the wanted similarity but for five standard deviations. Candidates form groups, and in a group each link is
confirmed by the exact similarity of the shingle sets, so that nothing below the wanted one is linked. So wide a radius rules
out cells of equal bits, as the short fingerprints use. Cells are named by content instead: each document goes to the cells
of its `KEYS` smallest shingle hashes, of which two documents at 0.8 share at least one but for a chance of about
0.2 ** 8. A cell of over `cap` fingerprints (a passage that very many documents hold) is split by the sizes of the shingle
sets: sets at the similarity have sizes in that ratio, so bands that wide and their neighbours suffice, and no pair is
lost. A band that is still larger is dealt in parts that meet pairwise. In a cell the fingerprints form a BK-tree that
all of them search at once; a spanning forest of the links comes back. The work of a hot cell grows with the square of
its largest band.

Equal shingle sets (128 bits of hash) are one node. Nulls and empty texts have no shingles, so they are one group. Repeated rows and null ids are
rows of their own. Only doc_id and text are read.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, prepare, rows, settle
from hotgraph.operators.components import components
from hotgraph.llm.simhash import shingle_hashes

BITS, KEYS = 1024, 8
#: An odd multiplier for each 64 bits of a fingerprint: powers of one constant.
_LANES = np.multiply.accumulate(np.full(BITS // 64, 0x9E3779B97F4A7C15, np.uint64))
#: Shingles whose bits are counted together, few enough for counts of one byte.
_STEP = 248
#: Sets of which the exact chance of a differing bit is taken: those with so many common shingles at most.
_SMALL = 40
#: Shingles in a part of a group whose links are confirmed: 8 MB.
_HELD = 1 << 20
_PRINT = pa.schema([
    ("doc_id", pa.int64()), ("tag", pa.int64()), ("sig", pa.binary()), ("fp", pa.binary()), ("keys", pa.list_(pa.int64())),
    ("size", pa.int64()), ("hashes", pa.binary()),
])
_LINK = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def _differs(common: int, a: int, b: int) -> float:
    """Chance that a bit differs between sets of so many common shingles and a and b of their own."""
    of = lambda n: [math.comb(n, k) / 2**n for k in range(n + 1)]
    out = 0.0
    for k, p in enumerate(of(common)):
        x = sum(q for j, q in enumerate(of(a)) if 2 * (k + j) > common + a)
        y = sum(q for j, q in enumerate(of(b)) if 2 * (k + j) > common + b)
        out += p * (x * (1 - y) + y * (1 - x))
    return out


def radius(similarity: float) -> int:
    """Bits that differ at most at a Jaccard similarity: the largest mean of any sizes and five standard deviations."""
    p = math.acos(2 * similarity / (1 + similarity)) / math.pi
    for common in range(1, _SMALL + 1):
        own = math.floor(common / similarity - common + 1e-9)
        p = max(p, *(_differs(common, a, n - a) for n in range(own + 1) for a in range(n // 2 + 1)))
    return min(BITS, math.ceil(BITS * p + 5 * math.sqrt(BITS * p * (1 - p))))


def fingerprint(text: str | None, words: int) -> tuple[bytes, bytes, list[int], int, bytes]:
    """Digest of the shingle set, all bits, the smallest shingle hashes as signed longs, number of shingles, all hashes.

    Each shingle counts once.
    """
    h = np.unique(shingle_hashes(text, words))
    whole = h.tobytes()
    sig = xxhash.xxh3_128_digest(whole)
    if not len(h):
        return sig, bytes(BITS // 8), [], 0, whole
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(h), _STEP):
        x = h[at : at + _STEP, None] * _LANES
        x ^= x >> np.uint64(32)
        x *= np.uint64(0x9FB21C651E98DF25)
        x ^= x >> np.uint64(29)
        ones += np.unpackbits(x.view(np.uint8).reshape(len(x), -1), axis=1).sum(0, dtype=np.uint8)
    return sig, np.packbits(ones * 2 > len(h)).tobytes(), h[:KEYS].view(np.int64).tolist(), len(h), whole


def fingerprints(docs: DataFrame, words: int = 5) -> DataFrame:
    """(doc_id, tag, sig, fp, keys, size, hashes) for each document."""
    prepare(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from emit(((doc, tag, *fingerprint(text, words)) for doc, text, tag in rows(batches)), _PRINT, 64)

    tagged = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("tag"))
    return tagged.mapInArrow(run, "doc_id bigint, tag bigint, sig binary, fp binary, keys array<bigint>, size bigint, hashes binary")


def alike(sets: list[bytes], similarity: float) -> Callable[[int, np.ndarray], np.ndarray]:
    """Which of some sets of 64-bit hashes have at least the Jaccard similarity with one, all given by their places."""
    size = np.array([len(s) // 8 for s in sets])
    start = np.cumsum(size) - size
    kinds, flat = np.unique(np.frombuffer(b"".join(sets), np.uint64), return_inverse=True)
    mark = np.zeros(len(kinds), bool)

    def same(node: int, near: np.ndarray) -> np.ndarray:
        mine = flat[start[node] : start[node] + size[node]]
        mark[mine] = True
        both = np.array([np.count_nonzero(mark[flat[start[k] : start[k] + size[k]]]) for k in near])
        mark[mine] = False
        return both >= similarity * (size[node] + size[near] - both) - 1e-9

    return same


def forest(prints: np.ndarray, most: int, same: Callable[[int, np.ndarray], np.ndarray] | None = None) -> Iterator[tuple[int, int]]:
    """Links of a spanning forest of the rows (64-bit lanes) at most so many bits apart, and the same if that is asked.

    The BK-tree is built and searched together: at a node all rows of its subtree get their distance, which is their
    edge, and of the rows that search here only those within the radius of an edge go down it.
    """
    label = np.arange(len(prints))
    todo = [(np.arange(len(prints)), np.arange(len(prints)))]
    while todo:
        tree, asking = todo.pop()
        node, below = tree[0], tree[1:]
        d = np.bitwise_count(prints[asking] ^ prints[node]).sum(1)
        near = asking[d <= most]
        if same is not None:
            near = near[label[near] != label[node]]
            near = near[same(int(node), near)] if len(near) else near
        for other in np.unique(label[near]):
            if other != label[node]:
                yield int(node), int(near[label[near] == other][0])
                label[label == other] = label[node]
        if len(below):
            edge = np.bitwise_count(prints[below] ^ prints[node]).sum(1)
            for e in np.unique(edge):
                down = asking[np.abs(d.astype(np.int64) - int(e)) <= most]
                if len(down):
                    todo.append((below[edge == e], down))


def _meets() -> Column:
    """The pairs of parts that a node's own part is in."""
    mine = F.pmod(F.xxhash64("node"), F.col("parts"))
    return F.transform(
        F.sequence(F.lit(0).cast("bigint"), F.col("parts").cast("bigint") - 1),
        lambda k: F.least(k, mine) * F.col("parts") + F.greatest(k, mine),
    )


def _cells(nodes: DataFrame, cap: int, similarity: float | None) -> DataFrame:
    """(key, part, node, fp) of all cells that hold more than one fingerprint."""
    band = F.lit(0) if similarity is None else F.floor(F.log(F.greatest("size", F.lit(1))) / max(1e-6, -1.0001 * math.log(similarity)))
    own = nodes.select("node", band.cast("int").alias("band"), F.explode("keys").alias("key"))
    shared = settle(own.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "shared")
    met = settle(own.join(shared, "key"), "met")
    usual = met.where(F.col("n") <= cap).select("key", "node", F.lit(1).alias("parts"))
    bands = F.array("band") if similarity is None else F.array("band", F.col("band") + 1)
    large = met.where(F.col("n") > cap).select("key", "node", F.explode(bands).alias("band"))
    large = settle(large.select(F.xxhash64("key", "band").alias("key"), "node"), "large")
    sizes = settle(large.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "sizes")
    large = large.join(sizes, "key").select("key", "node", F.ceil(F.col("n") / cap).cast("int").alias("parts"))
    dealt = usual.unionByName(large).select("key", F.explode(_meets()).alias("part"), "node")
    return dealt.join(nodes.select("node", "fp"), "node").select("key", "part", "node", "fp")


def _linked(dealt: DataFrame, most: int, similarity: float | None = None) -> DataFrame:
    """(a, b): the forests of the cells of dealt(key, part, node, fp), or with a similarity of (key, part, node, fp, hashes)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(held: list[tuple]) -> Iterator[tuple[int, int]]:
            if len(held) > 1:
                prints = np.frombuffer(b"".join(h[1] for h in held), np.uint64).reshape(len(held), -1)
                same = None if similarity is None else alike([h[2] for h in held], similarity)
                yield from ((held[a][0], held[b][0]) for a, b in forest(prints, most, same))

        def each() -> Iterator[tuple[int, int]]:
            last, held = None, []
            for key, part, *node in rows(batches, 8192 if similarity is None else 256):
                if (key, part) != last:
                    yield from done(held)
                    last, held = (key, part), []
                held.append(node)
            yield from done(held)

        yield from emit(each(), _LINK)

    return dealt.repartition("key", "part").sortWithinPartitions("key", "part", "node").mapInArrow(run, "a bigint, b bigint")


def links(nodes: DataFrame, most: int, cap: int = 4096, similarity: float | None = None) -> DataFrame:
    """(a, b): candidate links between nodes(node, fp, keys) that join what all links at most so many bits apart between
    nodes with a common key join. With a similarity, nodes also has the size of each set, and links between sets whose
    sizes rule the similarity out may be missing.
    """
    return _linked(_cells(nodes, cap, similarity), most)


def confirmed(named: DataFrame, nodes: DataFrame, prints: DataFrame, similarity: float, cap: int = 4096) -> DataFrame:
    """(a, b): links of at least the similarity, by the sets themselves, in the groups of candidates named(node, root)."""
    of = nodes.select("node", "fp", "size")
    members = settle(named.join(of, "node").select(F.col("root").alias("key"), "node", "fp", "size"), "members")
    parts = F.greatest(F.ceil(F.count("*") / cap), F.ceil(F.sum("size") / _HELD)).cast("int")
    groups = settle(members.groupBy("key").agg(parts.alias("parts")), "groups")
    dealt = settle(members.join(groups, "key").select("key", F.explode(_meets()).alias("part"), "node", "fp"), "dealt")
    return _linked(dealt.join(prints.select(F.col("row").alias("node"), "hashes"), "node").select("key", "part", "node", "fp", "hashes"), radius(similarity), similarity)


def similar(docs: DataFrame, words: int = 5, similarity: float = 0.8, cap: int = 4096) -> DataFrame:
    """(doc_id, tag, group) for each document; equal groups are linked by steps of at least the similarity."""
    prints = settle(fingerprints(docs, words).withColumn("row", F.monotonically_increasing_id()), "prints")
    nodes = settle(prints.groupBy("sig").agg(*(F.min(c).alias(n) for c, n in (("row", "node"), ("fp", "fp"), ("keys", "keys"), ("size", "size")))), "nodes")
    near = components(links(nodes, radius(similarity), cap, similarity))
    named = components(confirmed(near, nodes, prints, similarity, cap))
    each = settle(nodes.join(named, "node", "left").select("sig", F.coalesce("root", "node").alias("group")), "classes")
    return prints.select("doc_id", "tag", "sig").join(each, "sig", "left").select("doc_id", "tag", "group")
