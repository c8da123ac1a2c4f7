"""Benchmark decontamination: one Aho-Corasick automaton over the words of all test items.

Normal form: A-Z lower-cased, words are runs of letters, digits and non-ASCII characters. A window is `width`
consecutive words of an item; an item of fewer words, but not none, is one window. Items and documents become word
numbers, each two symbols of an alphabet of about the square root of the vocabulary, so that the automaton needs few
and small nodes. It holds the items' blocks of half a window, end to end: a window, wherever it begins, holds one whole,
so each document is scanned once and only the windows around a block that occurs are looked up by hash and then
compared word by word. Items shorter than a window are in the automaton as they are. Matches are mapped to word
numbers and to code points of the original text.

Nulls: a null text has no words; items whose id or text is null are not used. Repeated items share windows and
each is reported. An empty benchmark leaves every document clean. Repeated documents give one row each. Of
other columns only doc_id / text / item_id are read, so clashing names do no harm.
"""

from __future__ import annotations

import math
import uuid
from array import array
from collections.abc import Iterable, Iterator
from itertools import repeat

import ahocorasick
import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import WORD_TABLE, emit, prepare, rows

#: Bytes of item text in one automaton, under 500 MB of a worker's memory even where every word is a new one (a test
#: measures it); a larger benchmark is dealt to several, scanned in turn.
SHARD_BYTES = 8 << 20

SCHEMA = (
    "doc_id bigint, n_words bigint, n_hit bigint, items array<bigint>, "
    "spans array<struct<start: bigint, end: bigint, item_id: bigint>>"
)
_ARROW = pa.schema([
    ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("items", pa.list_(pa.int64())),
    ("spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("item_id", pa.int64())]))),
    ("tag", pa.int64()),
])


def normal_words(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(WORD_TABLE).split()


class Windows:
    """The windows of some items and the automaton that finds them."""

    def __init__(self, items: Iterable[tuple[int, str]], width: int) -> None:
        self.width, self.half, self.number = width, (width + 1) // 2, {}
        flat, at, owner, blocks, short = array("I"), array("q"), array("q"), array("q"), {}
        for item, text in items:
            words, first = normal_words(text), len(flat)
            flat.extend(self.number.setdefault(w, len(self.number) + 1) for w in words)
            if len(words) >= width:
                windows = range(first, len(flat) - width + 1)
                at.extend(windows)
                owner.extend(repeat(item, len(windows)))
                blocks.extend(range(first, len(flat) - self.half + 1, self.half))
            elif words:
                short.setdefault(tuple(flat[first:]), set()).add(item)
        self.flat = np.frombuffer(flat, np.uint32) if flat else np.empty(0, np.uint32)
        self.base = math.isqrt(len(self.number)) + 1
        self.short = [(len(words), tuple(sorted(ids))) for words, ids in short.items()]
        self._index(np.array(at, np.int64), np.array(owner, np.int64))
        self.tree = self._automaton(blocks, list(short))

    def _index(self, at: np.ndarray, owner: np.ndarray) -> None:
        """Distinct windows by hash: hashes in order, a place of each in flat, and the items of each."""
        for seed in range(64):
            self.mix = np.random.default_rng(seed).integers(0, 2**63, self.width, np.uint64) * np.uint64(2) + np.uint64(1)
            self.hashes, first, which = np.unique(self._hash(self.flat, at), return_index=True, return_inverse=True)
            self.place = at[first]
            if all((self.flat[self.place[which] + k] == self.flat[at + k]).all() for k in range(self.width)):
                break
        else:
            raise RuntimeError("no hash tells the windows apart")
        order = np.lexsort((owner, which))
        which, owner = which[order], owner[order]
        new = np.ones(len(which), bool)
        new[1:] = (which[1:] != which[:-1]) | (owner[1:] != owner[:-1])
        self.items = owner[new]
        self.bound = np.searchsorted(which[new], np.arange(len(self.place) + 1))

    def _hash(self, numbers: np.ndarray, at: np.ndarray) -> np.ndarray:
        out = np.zeros(len(at), np.uint64)
        for k in range(self.width):
            out += numbers[at + k].astype(np.uint64) * self.mix[k]
        return out

    def _symbols(self, numbers: np.ndarray) -> str:
        out = np.empty(2 * len(numbers), "<u4")
        out[0::2], out[1::2] = 1 + numbers // self.base, 1 + self.base + numbers % self.base
        return out.tobytes().decode("utf-32-le")

    def _automaton(self, blocks: Iterable[int], short: list[tuple[int, ...]]) -> ahocorasick.Automaton | None:
        """Values: 1 for a block, and twice the number of a short item, from 1, where the key is one."""
        if not blocks and not short:
            return None
        built = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        for start in blocks:
            built.add_word(self._symbols(self.flat[start : start + self.half]), 1)
        for k, words in enumerate(short, 1):
            key = self._symbols(np.array(words, np.uint32))
            built.add_word(key, 2 * k + (built.get(key, 0) & 1))
        built.make_automaton()
        return built

    def scan(self, text: str | None) -> tuple[int, list[tuple[int, int, tuple[int, ...]]]]:
        """Number of words, and (first word, word after the last, item ids) of each window found."""
        words = normal_words(text)
        if self.tree is None or not words:
            return len(words), []
        numbers = np.fromiter(map(self.number.get, words, repeat(0)), np.uint32, len(words))
        hits = list(self.tree.iter(self._symbols(numbers)))
        if not hits:
            return len(words), []
        end, value = np.array(hits, np.int64).T
        end = end // 2 + 1
        found = [(e - self.short[v - 1][0], e, self.short[v - 1][1]) for e, v in zip(end.tolist(), (value >> 1).tolist(), strict=True) if v]
        begun = end[value & 1 == 1] - self.half
        near = np.unique((begun[:, None] - np.arange(self.width - self.half + 1)).ravel())
        near = near[(near >= 0) & (near <= len(words) - self.width)]
        if len(near) and len(self.hashes):
            which = np.searchsorted(self.hashes, h := self._hash(numbers, near)).clip(max=len(self.hashes) - 1)
            good = self.hashes[which] == h
            for k in range(self.width):
                good &= self.flat[self.place[which] + k] == numbers[near + k]
            for a, w in zip(near[good].tolist(), which[good].tolist(), strict=True):
                found.append((a, a + self.width, tuple(self.items[self.bound[w] : self.bound[w + 1]].tolist())))
        return len(words), found


_built: dict[str, Windows] = {}


def windows(name: str, items: list[tuple[int, str]], width: int) -> Windows:
    """The windows of the items called so, made once in a worker process; the last ones only are kept."""
    if name not in _built:
        _built.clear()
        _built[name] = Windows(items, width)
    return _built[name]


def code_points(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each word in code points of the original text."""
    raw = text.encode()
    inside = np.concatenate([[0], (np.frombuffer(raw.translate(WORD_TABLE), np.uint8) != 0x20).view(np.int8), [0]])
    edge = np.diff(inside)
    point = np.concatenate([[0], np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)])
    return point[np.flatnonzero(edge == 1)], point[np.flatnonzero(edge == -1)]


def contamination(docs: DataFrame, benchmark: DataFrame, width: int = 10, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """One row for each document: SCHEMA. spans are the hit runs of words, in code points, with an item each.

    The benchmark's size is counted first. Up to shard_bytes its texts are broadcast and one automaton is made of them
    in each worker process; beyond that items are dealt to as many shards as needed, documents are scanned once with
    each shard's automaton, and the rows of a document are put together. One item is never split.
    """
    prepare(docs.sparkSession)
    parts = [_scanned(docs, items, width) for items in _shards(benchmark, shard_bytes)]
    return parts[0].drop("tag") if len(parts) == 1 else _merged(docs, parts)


def keep_clean(docs: DataFrame, benchmark: DataFrame, width: int = 10, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """docs in which no window occurs, with all their columns."""
    prepare(docs.sparkSession)
    for items in _shards(benchmark, shard_bytes):
        docs = docs.where(_clean(_broadcast(items), width)("text"))
    return docs


def _clean(held, width: int):  # noqa: ANN001, ANN202
    name = uuid.uuid4().hex

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        known = windows(name, held.value, width)
        for texts in batches:
            yield pd.Series([not known.scan(t)[1] for t in texts], dtype=bool)

    run.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return F.pandas_udf(run, "boolean")


def _shards(benchmark: DataFrame, shard_bytes: int) -> list[DataFrame]:
    """The items, dealt so that each part's texts are of bounded size."""
    items = benchmark.select(F.col("item_id").cast("bigint"), "text").where("item_id is not null and text is not null")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = -(-total // shard_bytes) or 1
    dealt = items.withColumn("shard", F.pmod(F.xxhash64("item_id", "text"), F.lit(shards)))
    return [dealt.where(F.col("shard") == k) for k in range(shards)]


def _broadcast(items: DataFrame):  # noqa: ANN202
    return items.sparkSession.sparkContext.broadcast([tuple(r) for r in items.select("item_id", "text").distinct().collect()])


def _scanned(docs: DataFrame, items: DataFrame, width: int) -> DataFrame:
    """One scan with the automaton of the given items, whose size is known to be bounded; tag tells texts apart."""
    held, name = _broadcast(items), uuid.uuid4().hex

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = windows(name, held.value, width)

        def each() -> Iterator[tuple]:
            for doc, text, tag in rows(batches):
                n, found = known.scan(text)
                hit, spans = np.zeros(n, bool), []
                for a, b, _ in found:
                    hit[a:b] = True
                if found:
                    start, end = code_points(text)
                    spans = sorted({(int(start[a]), int(end[b - 1]), i) for a, b, ids in found for i in ids})
                named = [{"start": a, "end": b, "item_id": i} for a, b, i in spans]
                yield doc, n, int(hit.sum()), sorted({i for _, _, i in spans}), named, tag

        yield from emit(each(), _ARROW, 512)

    tagged = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("tag"))
    return tagged.mapInArrow(run, f"{SCHEMA}, tag bigint")


def _merged(docs: DataFrame, parts: list[DataFrame]) -> DataFrame:
    """The shards' rows as one. Hit words are counted again, as runs of different shards may overlap."""
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    union = lambda c: F.array_sort(F.array_distinct(F.flatten(F.collect_list(c)))).alias(c)
    keyed = every.groupBy(F.col("doc_id").alias("d"), F.col("tag").alias("g")).agg(union("items"), union("spans"))
    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("tag"))
    joined = texts.join(keyed, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("tag") == F.col("g")))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def each() -> Iterator[tuple]:
            for doc, text, items, spans, tag in rows(batches):
                start, end = code_points(text or "")
                hit = np.zeros(len(start), bool)
                for s in spans:
                    hit |= (start >= s["start"]) & (end <= s["end"])
                yield doc, len(start), int(hit.sum()), items, spans, tag

        yield from emit(each(), _ARROW, 512)

    found = joined.select("doc_id", "text", "items", "spans", "tag").mapInArrow(run, f"{SCHEMA}, tag bigint")
    return found.drop("tag")


def digest(found: DataFrame) -> DataFrame:
    """The columns of the query's contract, from contamination()'s rows."""
    ids = F.array_sort(F.transform("items", lambda i: i.cast("string")))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join(ids, ",").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
    )
