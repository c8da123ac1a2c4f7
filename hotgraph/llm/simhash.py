"""SimHash near-duplicates: BK-trees over the distinct fingerprints, built in cells that bound their size.

A fingerprint has one bit of 64 set for each bit position that more than half of the shingles' hashes have set.
Equal fingerprints are one node, so copies cost nothing further. Two fingerprints that differ in at most R bits
agree on at least B - R of B blocks, so with B = R + 2 they share two whole blocks: each fingerprint goes to the
cells named by every pair of its blocks, and only cells are searched. In a cell the fingerprints form a BK-tree:
children are keyed by their Hamming distance to the parent, and a search follows only the edges within R of its
own distance. The named form broadcasts shard trees; a tree of all fingerprints grows with the data and has no
bound, so here tree and queries of a cell meet by a shuffle instead, and a cell of over `cap` fingerprints is
dealt in parts that meet pairwise. A cell yields a spanning forest of its links, never all pairs.

Nulls and empty texts have no words: fingerprint zero, linked like any other. A null doc_id keeps its row and never
names a component unless all its members have null ids. Repeated rows stay. Only doc_id and text are read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, fresh, prepare, rows, settle
from hotgraph.operators.components import components

SEED = 42  # fixed value
_FP = pa.schema([("doc_id", pa.int64()), ("tag", pa.int64()), ("fp", pa.int64())])
_LINK = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def shingle_hashes(text: str | None, words: int) -> np.ndarray:
    """XXH64 of each run of `words` words, repeats included; of the whole sequence where it is shorter."""
    w = (text or "").encode().lower().split()
    if not w:
        return np.empty(0, "<u8")
    if len(w) <= words:
        return np.array([xxhash.xxh64_intdigest(b" ".join(w), SEED)], "<u8")
    flat, hashed = b" ".join(w), xxhash.xxh64_intdigest
    end = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    start = np.concatenate([[0], end[: -words] + 1]).tolist()
    return np.array([hashed(flat[a:b], SEED) for a, b in zip(start, end[words - 1 :].tolist(), strict=True)], "<u8")


def fingerprint(text: str | None, words: int) -> int:
    """Unsigned 64-bit fingerprint."""
    h = shingle_hashes(text, words)
    if not len(h):
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, len(h), 1 << 16):
        part = h[at : at + (1 << 16)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, words: int = 3) -> DataFrame:
    """(doc_id, tag, fp) for each document; fp holds the 64 bits as a signed long, tag tells texts of one id apart."""
    prepare(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signed = lambda x: x - (1 << 64) if x >> 63 else x
        yield from emit(((doc, tag, signed(fingerprint(text, words))) for doc, text, tag in rows(batches)), _FP)

    tagged = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("tag"))
    return tagged.mapInArrow(run, "doc_id bigint, tag bigint, fp bigint")


class BKTree:
    """Burkhard-Keller tree over distinct 64-bit values. Node k holds value[k]; child[k] maps a distance to a node."""

    def __init__(self) -> None:
        self.value: list[int] = []
        self.child: list[dict[int, int]] = []

    def add(self, x: int) -> None:
        at = 0 if self.value else None
        self.value.append(x)
        self.child.append({})
        while at is not None:
            d = (self.value[at] ^ x).bit_count()
            if (to := self.child[at].get(d)) is None:
                self.child[at][d] = len(self.value) - 1
            at = to

    def within(self, x: int, radius: int) -> Iterator[int]:
        """Numbers of the nodes at most radius away."""
        todo = [0] if self.value else []
        while todo:
            at = todo.pop()
            d = (self.value[at] ^ x).bit_count()
            if d <= radius:
                yield at
            edges = self.child[at]
            todo += [to for e, to in edges.items() if d - radius <= e <= d + radius]


def forest(values: list[int], radius: int) -> Iterator[tuple[int, int]]:
    """Links of a spanning forest of the values' links within radius: each value is sought, then added."""
    up = list(range(len(values)))

    def root(k: int) -> int:
        while up[k] != k:
            up[k] = up[up[k]]
            k = up[k]
        return k

    tree = BKTree()
    for k, x in enumerate(values):
        for other in tree.within(x, radius):
            if (a := root(other)) != (b := root(k)):
                up[b] = a
                yield values[other], x
        tree.add(x)


def _cells(distinct: DataFrame, radius: int, cap: int) -> DataFrame:
    """(route, key, part, fp): the cells of each fingerprint; large cells in pairs of parts."""
    blocks = radius + 2
    edges = [64 * k // blocks for k in range(blocks + 1)]
    block = [
        F.expr(f"shiftrightunsigned(fp, {a}) & {(1 << (b - a)) - 1}L") for a, b in zip(edges, edges[1:], strict=False)
    ]
    routes = F.array(*(
        F.struct(F.lit(k).alias("route"), (block[i] * F.lit(1 << 32) + block[j]).alias("key"))
        for k, (i, j) in enumerate(combinations(range(blocks), 2))
    ))
    cells = distinct.select("fp", F.explode(routes).alias("c")).select("c.route", "c.key", "fp")
    large = settle(cells.groupBy("route", "key").count().where(F.col("count") > cap), "large")
    if large.isEmpty():
        return cells.withColumn("part", F.lit(0).cast("bigint"))
    parts = F.ceil(F.coalesce(F.col("count"), F.lit(1)) / cap)
    mine = F.pmod(F.xxhash64("fp"), parts)
    pairs = F.transform(
        F.sequence(F.lit(0).cast("bigint"), parts - 1), lambda k: F.least(k, mine) * parts + F.greatest(k, mine)
    )
    return cells.join(large, ["route", "key"], "left").select("route", "key", F.explode(pairs).alias("part"), "fp")


def links(distinct: DataFrame, radius: int = 2, cap: int = 4096) -> DataFrame:
    """(a, b): links within the radius that join the same fingerprints as all links do. distinct has one row a fp."""
    prepare(distinct.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = (1 << 64) - 1

        def each() -> Iterator[tuple[int, int]]:
            last, held = None, []
            for *cell, fp in rows(batches, 65536):
                if cell != last:
                    if len(held) > 1:
                        yield from forest(held, radius)
                    last, held = cell, []
                held.append(fp & mask)
            if len(held) > 1:
                yield from forest(held, radius)

        signed = lambda x: x - (1 << 64) if x >> 63 else x
        yield from emit(((signed(a), signed(b)) for a, b in each()), _LINK)

    cell = ["route", "key", "part"]
    dealt = _cells(distinct, radius, cap).select(*cell, "fp").repartition(*cell).sortWithinPartitions(*cell, "fp")
    return dealt.mapInArrow(run, "a bigint, b bigint")


def classes(prints: DataFrame, radius: int = 2) -> DataFrame:
    """(doc_id, tag, fp, group, component_id) for each row of prints(doc_id, tag, fp), which has been written already.

    group is the least fingerprint of the component, component_id the least doc_id.
    """
    distinct = settle(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    named = components(links(distinct.select("fp"), radius)).withColumnRenamed("node", "fp")
    linked = settle(named.join(distinct, "fp").select("fp", "root", "least"), "linked")
    roots = linked.groupBy("root").agg(F.min("least").alias("component_id"))
    of = linked.join(roots, "root").select("fp", "root", "component_id")
    each = distinct.join(of, "fp", "left").select(
        "fp", F.coalesce("root", "fp").alias("group"), F.coalesce("component_id", "least").alias("component_id")
    )
    # Written, so that the join's sides are plain shuffles and a common fingerprint can be split.
    return prints.join(settle(each, "classes"), "fp", "left").select("doc_id", "tag", "fp", "group", "component_id")


def near_duplicates(docs: DataFrame, words: int = 3, radius: int = 2) -> DataFrame:
    """(doc_id, tag, fp, group, component_id) for each document."""
    return classes(settle(fingerprints(docs, words), "prints"), radius)


def keep_first(docs: DataFrame, found: DataFrame) -> DataFrame:
    """docs with one row of each group of found(doc_id, tag, group): the smallest doc_id (null ids last), then tag."""
    found = settle(found.select("doc_id", "tag", "group"), "groups")
    rank = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "tag")
    # Written, so that the join's sides are plain shuffles and a large group can be split.
    first = settle(found.groupBy(F.col("group").alias("g")).agg(F.min(rank).alias("first")), "first")
    stays = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("tag") == F.col("first.tag"))
    met = found.join(first, F.col("group") == F.col("g"))
    gone = settle(met.where(~stays).select("doc_id", "tag").distinct(), "gone")
    again = settle(found.groupBy("doc_id", "tag").count().where("count > 1").select("doc_id", "tag"), "again")
    left = _without(docs, gone)
    if again.isEmpty():
        return left
    d, t, own = fresh(docs, "_doc", "_tag", "_own")
    keyed = left.withColumn(own, F.xxhash64("text")).join(
        again.select(F.col("doc_id").alias(d), F.col("tag").alias(t)),
        F.col("doc_id").cast("bigint").eqNullSafe(F.col(d)) & (F.col(own) == F.col(t)), "left_semi",
    )
    return _without(left, again).unionByName(keyed.dropDuplicates(["doc_id", own]).select(*docs.columns))


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """docs without the rows named by ids(doc_id, tag); the ids are the hashed side, so that texts are never sorted."""
    d, t = fresh(docs, "_doc", "_tag")
    ids = ids.select(F.col("doc_id").alias(d), F.col("tag").alias(t))
    limit = docs.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
    known = int(str(ids._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    side = ids if known <= limit else ids.hint("shuffle_hash")
    on = F.col("doc_id").cast("bigint").eqNullSafe(F.col(d)) & (F.xxhash64("text") == F.col(t))
    return docs.join(side, on, "left_anti")


def digest(found: DataFrame) -> DataFrame:
    """The columns of the query's contract, from near_duplicates()'s rows."""
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
