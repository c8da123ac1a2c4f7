"""MD5 of many short texts at once: which of them begin under a bound. RFC 1321, 32-bit words in arrays."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Texts of one size that are hashed together: enough that a step's calls cost little, few enough that words stay in the cache.
LANES = 1 << 15
#: Rows that are collected before they are hashed; with fewer, the sizes that are not frequent fill no LANES.
ROWS = 1 << 18
#: Bytes of a text up to which it fills one block with its end mark and length.
SHORT = 55

_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_ADDED = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_PLACES = [*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *((7 * i) % 16 for i in range(16))]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _stepped(words: list[np.ndarray | int], state: list[np.ndarray], first: int, last: int) -> list[np.ndarray]:
    """state, whose arrays are overwritten, after the steps first..last - 1."""
    a, b, c, d = state
    f = np.empty(len(a), np.uint32)
    for i in range(first, last):
        kind = i // 16
        if kind == 0:
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif kind == 1:
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif kind == 2:
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        word, more = words[_PLACES[i]], _ADDED[i]
        np.add(f, a, out=f)
        if isinstance(word, np.ndarray):
            np.add(f, word, out=f)
        else:
            more += word
        np.add(f, np.uint32(more & 0xFFFFFFFF), out=f)
        turn = _TURNS[kind][i % 4]
        np.left_shift(f, np.uint32(turn), out=a)
        np.right_shift(f, np.uint32(32 - turn), out=f)
        np.bitwise_or(a, f, out=a)
        np.add(a, b, out=a)
        a, b, c, d = d, a, b, c
    return [a, b, c, d]


def _leading(messages: list[list[np.ndarray | int]], n: int, alike: int) -> Iterator[np.ndarray]:
    """For each message of 16 words, arrays of n or one value for all: the first 32 bits of its MD5, as they are read in
    hexadecimal. alike: words at the start that are the same in all messages, whose steps are made once.
    """
    begun = _stepped(messages[0], [np.full(n, x, np.uint32) for x in _START], 0, alike)
    for words in messages:
        end = _stepped(words, [x.copy() for x in begun], alike, 61)  # the last three steps leave the first word as it is
        yield (end[1] + np.uint32(_START[0])).byteswap()


def below(texts: pa.Array, salts: list[bytes], bound: int | list[int]) -> Iterator[tuple[int, np.ndarray]]:
    """(place of the salt, places of the texts) where the MD5 of a text and a salt begins with 32 bits under the bound, or
    under the salt's own.
    """
    bounds = [bound] * len(salts) if isinstance(bound, int) else bound
    texts = pa.concat_arrays([texts]).cast(pa.binary())
    starts = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1]
    held, sizes = np.frombuffer(texts.buffers()[2], np.uint8), np.diff(starts)
    longest = max(map(len, salts))
    for size in np.unique(sizes).tolist():
        alike = np.flatnonzero(sizes == size)
        if size + longest > SHORT:
            for k, salt in enumerate(salts):
                first = lambda i: int(hashlib.md5(texts[int(i)].as_py() + salt).hexdigest()[:8], 16)  # noqa: B023, E731, S324
                yield k, np.array([i for i in alike if first(i) < bounds[k]], np.int64)
            continue
        ends = [bytes(size) + salt + b"\x80" for salt in salts]
        ends = [np.frombuffer(e.ljust(56, b"\0") + (8 * (len(e) - 1)).to_bytes(8, "little"), "<u4").tolist() for e in ends]
        shared = next((i for i in range(16) if any(e[i] != ends[0][i] for e in ends)), 16)
        for rows in np.array_split(alike, -(-len(alike) // LANES)):
            block = np.zeros((len(rows), 64), np.uint8)
            block[:, :size] = held[starts[rows, None] + np.arange(size)]
            lanes = np.ascontiguousarray(block.view("<u4").T[: -(-size // 4)]).astype(np.uint32)
            mixed = {(i, e[i]): lanes[i] + np.uint32(e[i]) if e[i] else lanes[i] for e in ends for i in range(len(lanes))}
            messages = [[mixed[i, x] if i < len(lanes) else x for i, x in enumerate(e)] for e in ends]
            for k, found in enumerate(_leading(messages, len(rows), shared)):
                yield k, rows[found < bounds[k]]


def pairs_below(salts: list[str], bound: int | list[int], first: int = 1) -> Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Of rows (src, dst, since): (src, dst, batch) for the batches after since, with a salt each from the first on, where
    the key src-dst-salt begins under the bound.
    """
    ends = [f"-{salt}".encode() for salt in salts]

    def found(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(held).combine_chunks()
        texts = pc.binary_join_element_wise(t["src"].cast(pa.string()), t["dst"].cast(pa.string()), "-").combine_chunks()
        src, dst, since = (t[c].to_numpy() for c in ("src", "dst", "since"))
        hits = [(k, rows) for k, rows in below(texts.chunk(0) if isinstance(texts, pa.ChunkedArray) else texts, ends, bound) if len(rows)]
        rows = np.concatenate([np.empty(0, np.int64), *(rows for _, rows in hits)])
        batch = np.repeat(np.array([first + k for k, _ in hits], np.int32), [len(rows) for _, rows in hits])
        open_ = since[rows] < batch
        rows, batch = rows[open_], batch[open_]
        yield pa.RecordBatch.from_arrays([pa.array(src[rows]), pa.array(dst[rows]), pa.array(batch)], ["src", "dst", "batch"])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            held.append(b)
            n += b.num_rows
            if n >= ROWS:
                yield from found(held)
                held, n = [], 0
        if n:
            yield from found(held)

    return run
