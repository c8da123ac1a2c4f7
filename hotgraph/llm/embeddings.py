"""Embedding near-dedup: an exact metric range join of unit vectors.

Cosine at least s means a distance of at most r = sqrt(2 - 2 s) between unit vectors. Pivots split the space: a vector's
home is its nearest pivot. Let y have another home than x, and link to x: the triangle inequality gives
d(y, home of x) <= d(y, home of y) + 2 r, and the plane half-way between the two pivots is at most r from y, which is
tighter; and d(y, p) is at most r over the largest distance from p of its own members. A vector is sent to each
lower-numbered cell that these bounds leave open, so a pair meets once. Pivots are chosen far apart among a bounded
sample. Cells are joined independently, in blocks of home vectors by members that `BLOCK_BYTES` sizes, so a crowded cell
is many tasks. A block returns, for each vector, its number of links and one link to the least node it reaches there,
never all pairs. Equal vectors are one node. Vectors of 32-bit floats travel as such, which loses nothing; all
decisions are made in double precision.

Vectors that are null, zero, or hold null or non-finite components link with nothing, and vectors of different lengths
never link. A null vec_id keeps its row. Repeated vec_ids are rows of their own. Only vec_id and embedding are read.
The bounds prune by what structure the vectors have; without any, all cells stay open and the work is that of all pairs.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, prepare, rows, settle
from hotgraph.operators.components import components

#: Slack on the bounds, far above the rounding of doubles and far below any distance that matters.
EPS = 1e-6
#: Vectors to a pivot, the most pivots (these are broadcast), and how many vectors they are chosen among, for each pivot.
PER_PIVOT, MOST_PIVOTS, AMONG = 16384, 1024, 4
#: Bytes of one side of a block, as doubles, and of a part of its products.
BLOCK_BYTES, PART = 8 << 20, 1 << 22
#: Most partitions that blocks are dealt to.
MOST_TASKS = 20_000

_KEYED = pa.schema([("vec_id", pa.int64()), ("key", pa.binary()), ("dim", pa.int32()), ("v", pa.binary())])
_CELL = pa.schema([("node", pa.int64()), ("dim", pa.int32()), ("cell", pa.int32()), ("home", pa.bool_()), ("n", pa.int64()), ("v", pa.binary())])
_FOUND = pa.schema([("node", pa.int64()), ("to", pa.int64()), ("n", pa.int64())])


def _keyed(vectors: DataFrame) -> DataFrame:
    """(vec_id, key, dim, v): v holds the components as they came and key its digest; null for those that never link."""
    kind = "float" if dict(vectors.dtypes)["embedding"] == "array<float>" else "double"

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def each() -> Iterator[tuple]:
            for batch in batches:
                ids, lists = batch.column(0).to_pylist(), batch.column(1)
                values = lists.values.to_numpy(zero_copy_only=False) + np.float32(0)  # null is nan, -0 is 0
                at, there = lists.offsets.to_numpy(), lists.is_valid().to_numpy(zero_copy_only=False)
                for k, vec in enumerate(ids):
                    x = values[at[k] : at[k + 1]]
                    if there[k] and len(x) and np.isfinite(x).all() and x.any():
                        raw = x.tobytes()
                        yield vec, hashlib.blake2b(raw, digest_size=16).digest(), len(x), raw
                    else:
                        yield vec, None, None, None

        yield from emit(each(), _KEYED, 1024)

    picked = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").cast(f"array<{kind}>").alias("embedding"))
    return picked.mapInArrow(run, "vec_id bigint, key binary, dim int, v binary")


def _unit(raw: list[bytes], dim: int) -> np.ndarray:
    x = np.frombuffer(b"".join(raw), f"<f{len(raw[0]) // dim}").reshape(len(raw), dim).astype(float)
    x /= np.abs(x).max(1, keepdims=True)  # neither overflow nor underflow in the norm
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    return x


def _pivots(nodes: DataFrame, want: int) -> dict[int, list[bytes]]:
    """`want` vectors by their length, chosen far apart among a sample: each is the farthest from those before it."""
    sample: dict[int, list[bytes]] = {}
    few = nodes.orderBy("key").select("dim", "v").limit(want * AMONG).collect()  # at most MOST_PIVOTS * AMONG vectors
    for row in few:
        sample.setdefault(row.dim, []).append(bytes(row.v))
    out = {}
    for dim, raw in sample.items():
        x = _unit(raw, dim)
        near, picked = np.full(len(x), 9.0), [0]
        for _ in range(round(want * len(x) / len(few)) - 1):
            near = np.minimum(near, _distances(x, x[picked[-1:]])[:, 0])
            picked.append(int(near.argmax()))
        out[dim] = [raw[k] for k in picked]
    return out


def _distances(x: np.ndarray, p: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(2 - 2 * (x @ p.T), 0))


def _route(nodes: DataFrame, pivots: dict[int, list[bytes]], reach: dict[tuple[int, int], float] | None, r: float) -> DataFrame:
    """Cells of each node. With reach None: only its home, and its distance as bytes in v."""
    held = nodes.sparkSession.sparkContext.broadcast((pivots, reach))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, far = held.value
        p = {dim: _unit(v, dim) for dim, v in raw.items()}

        def each() -> Iterator[tuple]:
            for batch in batches:
                by: dict[int, list[tuple]] = {}
                for node, dim, n, v in rows([batch]):
                    by.setdefault(dim, []).append((node, n, v))
                for dim, some in by.items():
                    if dim not in p:  # too rare for a pivot: one cell, cut into blocks like any other
                        yield from ((node, dim, 0, True, n, v if far is not None else np.float64(2).tobytes()) for node, n, v in some)
                        continue
                    d = _distances(_unit([v for _, _, v in some], dim), p[dim])
                    home = d.argmin(1)
                    own = d[np.arange(len(some)), home]
                    if far is None:
                        yield from ((node, dim, int(c), True, n, np.float64(x).tobytes()) for (node, n, _), c, x in zip(some, home, own, strict=True))
                        continue
                    apart = _distances(p[dim], p[dim])[home]
                    open_ = (d <= own[:, None] + 2 * r + EPS) & (d <= np.array([far.get((dim, c), -9.0) for c in range(d.shape[1])]) + r + EPS)
                    open_ &= (d**2 - own[:, None] ** 2) <= 2 * apart * r + EPS
                    open_ &= np.arange(d.shape[1]) < home[:, None]
                    for (node, n, v), c, row in zip(some, home, open_, strict=True):
                        yield node, dim, int(c), True, n, v
                        yield from ((node, dim, int(k), False, n, v) for k in np.flatnonzero(row))

        yield from emit(each(), _CELL, 1024)

    return nodes.select("node", "dim", "n", "v").mapInArrow(run, "node bigint, dim int, cell int, home boolean, n bigint, v binary")


def _block(ids: list[np.ndarray], unit: list[np.ndarray], own: np.ndarray, sizes: list[np.ndarray], least: float) -> Iterator[tuple]:
    """Links between the home vectors (0) and the members (1) of one block. own: members that are at home here.

    Products come in parts; of each only sums and the classes it joins are kept.
    """
    every, at = np.unique(np.concatenate(ids), return_inverse=True)
    at0, at1 = at[: len(ids[0])], at[len(ids[0]) :]
    root, n0, n1 = np.arange(len(every)), np.zeros(len(ids[0])), np.zeros(len(ids[1]))
    single, slack = unit[1].T.astype(np.float32), 1e-4 + 2e-7 * unit[0].shape[1]
    step = max(1, PART // len(ids[1]))
    for first in range(0, len(ids[0]), step):
        cos = unit[0][first : first + step].astype(np.float32) @ single
        a, b = np.nonzero(cos >= least - slack)
        cos = cos[a, b]
        a += first
        good = cos >= least + slack
        close = np.flatnonzero(~good)  # too near the bound for single precision
        for k in range(0, len(close), 1 << 16):
            some = close[k : k + (1 << 16)]
            good[some] = np.einsum("ij,ij->i", unit[0][a[some]], unit[1][b[some]]) >= least
        good &= at0[a] != at1[b]
        a, b = a[good], b[good]
        n0 += np.bincount(a, weights=sizes[1][b], minlength=len(n0))
        n1 += np.bincount(b, weights=sizes[0][a], minlength=len(n1))
        _join(root, at0[a], at1[b])
    to = every[root]
    yield from ((int(x), int(t), int(n)) for x, t, n in zip(ids[0], to[at0], n0, strict=True) if n)
    yield from ((int(x), int(t), 0 if o else int(n)) for x, t, n, o in zip(ids[1], to[at1], n1, own, strict=True) if n and not (o and x == t))


def _join(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """root (the least member of each one's class) after the links a - b."""
    while True:
        x, y = root[a], root[b]
        apart = x != y
        if not apart.any():
            return
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root[:] = root[root]


def links(nodes: DataFrame, least: float, block: int | None = None) -> DataFrame:
    """(node, to, n): partial numbers of linked vectors, and a node reached, from each block. nodes: node, dim, n, v."""
    prepare(nodes.sparkSession)
    r = float(np.sqrt(2 - 2 * least))
    count = nodes.count()
    want = min(MOST_PIVOTS, max(1, count // PER_PIVOT))
    pivots = _pivots(nodes, want)
    far = _farthest(_route(nodes, pivots, None, r))
    cells = settle(_route(nodes, pivots, far, r), "cells")
    rows_of = F.lit(block) if block else F.greatest(F.lit(64), F.floor(F.lit(BLOCK_BYTES) / (8 * F.col("dim"))))
    sizes = cells.groupBy("dim", "cell").agg(F.count("*").alias("m"), F.sum(F.col("home").cast("bigint")).alias("h"))
    size = settle(sizes.select("dim", "cell", F.ceil(F.col("h") / rows_of).alias("ph"), F.ceil(F.col("m") / rows_of).alias("pm")), "blocks")
    tasks = size.agg(F.sum(F.col("ph") * F.col("pm"))).first()[0] or 1
    tasks = min(MOST_TASKS, max(int(tasks), int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    cells = cells.join(size, ["dim", "cell"])
    some = lambda n: F.sequence(F.lit(0).cast("bigint"), n - 1)
    pick = lambda n: F.pmod(F.xxhash64("node"), n)
    as_home = cells.where("home").select("dim", "cell", pick(F.col("ph")).alias("i"), F.explode(some(F.col("pm"))).alias("j"), F.lit(0).alias("side"), "node", "home", "n", "v")
    as_member = cells.where("ph > 0").select("dim", "cell", F.explode(some(F.col("ph"))).alias("i"), pick(F.col("pm")).alias("j"), F.lit(1).alias("side"), "node", "home", "n", "v")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(dim: int, held: list[list[tuple]]) -> Iterator[tuple]:
            if held[0] and held[1]:
                ids = [np.array([x[0] for x in h], np.int64) for h in held]
                sizes = [np.array([x[2] for x in h], np.float64) for h in held]
                unit = [_unit([x[3] for x in h], dim) for h in held]
                yield from _block(ids, unit, np.array([x[1] for x in held[1]], bool), sizes, least)

        def each() -> Iterator[tuple]:
            last, held = (0,), [[], []]
            for dim, cell, i, j, side, *row in rows(batches):
                if (dim, cell, i, j) != last:
                    yield from done(last[0], held)
                    last, held = (dim, cell, i, j), [[], []]
                held[side].append(row)
            yield from done(last[0], held)

        yield from emit(each(), _FOUND)

    by = ["dim", "cell", "i", "j"]
    dealt = as_home.unionByName(as_member).repartition(tasks, *by).sortWithinPartitions(*by, "side", "node")
    return dealt.select(*by, "side", "node", "home", "n", "v").mapInArrow(run, "node bigint, to bigint, n bigint")


def _farthest(at_home: DataFrame) -> dict[tuple[int, int], float]:
    """Largest distance from its pivot that each cell's own vectors have; one number a cell."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        most: dict[tuple[int, int], float] = {}
        for _, dim, cell, _, _, v in rows(batches):
            most[dim, cell] = max(most.get((dim, cell), 0.0), float(np.frombuffer(v, "<f8")[0]))
        yield from emit(((*k, x) for k, x in most.items()), pa.schema([("dim", pa.int32()), ("cell", pa.int32()), ("x", pa.float64())]))

    parts = at_home.mapInArrow(run, "dim int, cell int, x double")
    return {(r.dim, r.cell): r.x for r in parts.groupBy("dim", "cell").agg(F.max("x").alias("x")).collect()}


def near_duplicates(vectors: DataFrame, least: float = 0.9, block: int | None = None) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of vectors(vec_id, embedding)."""
    prepare(vectors.sparkSession)
    keyed = settle(_keyed(vectors), "vectors")
    distinct = keyed.where("key is not null").groupBy("key").agg(
        F.count("*").alias("n"), F.min("vec_id").alias("least"), F.first("dim").alias("dim"), F.first("v").alias("v")
    )
    nodes = settle(distinct.withColumn("node", F.monotonically_increasing_id()), "nodes")
    found = settle(links(nodes, least, block), "found")
    degree = found.groupBy("node").agg(F.sum("n").alias("outer"))
    named = components(found.select(F.col("node").alias("a"), F.col("to").alias("b")))
    linked = settle(named.join(nodes.select("node", "least"), "node"), "linked")
    roots = linked.groupBy("root").agg(F.min("least").alias("component_id"))
    of = linked.join(roots, "root").select("node", "component_id")
    each = (
        nodes.select("key", "node", "n", "least").join(degree, "node", "left").join(of, "node", "left")
        .select("key", (F.coalesce("outer", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component_id", "least").alias("component_id"))
    )
    out = keyed.select("vec_id", "key").join(each, "key", "left")
    component = F.coalesce("component_id", "vec_id")
    return out.select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), component.alias("component_id"),
        F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"),
    )
