"""Best-fit packing by minimum bin slack, on the histogram of piece lengths.

Documents become token ids plus one end id; longer ones than a sequence are cut into full pieces from the end, so
the first piece may be shorter. All that the choice of bins needs is how many pieces there are of each length, at
most `capacity` numbers whatever the input. For the fullest bin, the largest length left opens it and a subset-sum
over a bitset of reachable fillings (one bit a token) finds the fullest combination of the lengths left, each as
often as there are pieces; that combination is removed as often as the counts allow, and so on. The plan is a
short table of intervals of ranks. Pieces are numbered when they are written and get their rank inside their length by
groups salted with that number, so neither a common length nor repeated rows make one large group, and the number of
groups grows with the pieces. They look up their interval by a broadcast join.

A null text is empty: one piece of one token. Repeated rows are packed each. Only doc_id and text are read.
"""

from __future__ import annotations

import base64
import re
import zlib
from collections import Counter
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, prepare, rows, settle

CAPACITY, END = 1024, 2  # fixed values
#: Entries that a worker's cache of words may hold.
WORDS_HELD = 400_000
#: Rows of a salted group: at least and at most. Between them there are `GROUPS` groups.
LEAST, MOST, GROUPS = 512, 100_000, 4096
#: Groups whose first ranks may be broadcast, at three longs each.
BASES = 200_000
_PIECE = pa.schema([
    ("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()),
])
PIECE = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"


class Encoder:
    """Ids of the byte-level BPE as little-endian unsigned 32-bit bytes, the same as the tokenizer file's own.

    A text is split at single spaces and line ends, where this vocabulary's pattern always splits, and the words'
    ids come from a cache. Texts with a run of two or more white-space characters of any kind (a no-break space may be
    one) are not split, and what is outside Latin goes through the file's tokenizer. The tokenizer's special string in
    a text is its special id, as in the file.
    """

    #: Where a cut at the space could differ from the pattern.
    ODD = re.compile(r"\s\s")

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.special = {t.content: i for i, t in self.whole.get_added_tokens_decoder().items()}
        self.fast = self._ranks(path)
        self.words: dict[str, bytes] = {}

    @staticmethod
    def _ranks(path: str):  # noqa: ANN205
        """The same vocabulary for the quicker library where its file lies beside; else None."""
        try:
            import public_tokenizers
            import tiktoken

            with open(re.sub(r"\.json$", ".tiktoken", path), "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        except (ImportError, OSError):
            return None

    def _plain(self, text: str) -> bytes:
        if self.fast is not None and (text.isascii() or max(text) < "ɐ"):
            return np.array(self.fast.encode_ordinary(text), "<u4").tobytes()
        return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _word(self, word: str) -> bytes:
        if len(self.words) >= WORDS_HELD:
            self.words.clear()
        got = self._plain(word if word[:1] == "\n" else f" {word}")
        if len(word) < 64:
            self.words[word] = got
        return got

    def __call__(self, text: str) -> bytes:
        if any(s in text for s in self.special):
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        if self.ODD.search(text):
            return self._plain(text)
        first, *more = text.replace("\n", " \n").split(" ")
        held = self.words.get
        return self._plain(first) + b"".join([held(w) or self._word(w) for w in more])


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """The encoder of a file, made once in a worker process."""
    return Encoder(path)


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """PIECE rows of each document. The tokenizer's path must exist on the executors."""
    prepare(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        last = int(end).to_bytes(4, "little")

        def each() -> Iterator[tuple]:
            for doc, text in rows(batches):
                ids = (encode(text) if text else b"") + last
                n, at = len(ids) // 4, 0
                for piece in range(-(-n // capacity)):
                    to = at + (capacity if at else n % capacity or capacity)
                    yield doc, piece, at, to - at, zlib.crc32(memoryview(ids)[4 * at : 4 * to])
                    at = to

        yield from emit(each(), _PIECE)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(run, PIECE)


def fullest(left: Counter, capacity: int) -> dict[int, int]:
    """The fullest combination that holds the largest length left: {length: how often}."""
    lengths = sorted(left, reverse=True)
    seed = lengths[0]
    room, mask, steps = capacity - seed, (1 << (capacity - seed + 1)) - 1, []
    reach = 1
    for length in lengths:
        if reach >> room & 1:
            break
        often, chunk = min(left[length] - (length == seed), room // length), 1
        while often > 0:
            take = min(chunk, often)
            steps.append((reach, length, take))
            reach |= reach << take * length & mask
            often, chunk = often - take, chunk * 2
    used, filled = Counter({seed: 1}), reach.bit_length() - 1
    for before, length, take in reversed(steps):
        if not before >> filled & 1:
            used[length] += take
            filled -= take * length
    return dict(used)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, dict[int, int]]]:
    """(how many bins, {length: how often in each}) until nothing is left."""
    left, out = Counter({k: v for k, v in histogram.items() if v > 0}), []
    while left:
        used = fullest(left, capacity)
        bins = min(left[length] // n for length, n in used.items())
        out.append((bins, used))
        for length, n in used.items():
            left[length] -= n * bins
            if not left[length]:
                del left[length]
    return out


def intervals(bins: list[tuple[int, dict[int, int]]]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, rank after the last, pieces to a bin, first bin, offset of the first of them)."""
    rank, first, out = Counter(), 0, []
    for count, used in bins:
        offset = 0
        for length, n in used.items():
            out.append((length, rank[length], rank[length] + n * count, n, first, offset))
            rank[length] += n * count
            offset += n * length
        first += count
    return out


def numbered(cut: DataFrame) -> DataFrame:
    """cut written with a number for each row, which later reads of it agree on."""
    return settle(cut.withColumn("row", F.monotonically_increasing_id()), "pieces")


def pack(cut: DataFrame, capacity: int = CAPACITY, group: int | None = None, bases_held: int = BASES) -> DataFrame:
    """cut (PIECE rows, from numbered()) with sequence_id and offset. group: rows of a salted group, else by size."""
    spark = cut.sparkSession
    counts = {r.length: r.n for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most capacity rows
    size = group or min(MOST, max(LEAST, -(-sum(counts.values()) // GROUPS)))
    parts = {k: -(-v // size) for k, v in counts.items()}
    salts = spark.createDataFrame(list(parts.items()), "length bigint, salts bigint")
    salted = cut.join(F.broadcast(salts), "length").withColumn("salt", F.pmod(F.xxhash64("row"), F.col("salts")))
    by = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    bases = (
        salted.groupBy("length", "salt").agg(F.count("*").alias("n"))  # a row a group
        .select("length", "salt", F.coalesce(F.sum("n").over(by), F.lit(0)).alias("base"))
    )
    if sum(parts.values()) <= bases_held:
        bases = F.broadcast(bases)
    within = Window.partitionBy("length", "salt").orderBy("row")
    ranked = (
        salted.withColumn("k", F.row_number().over(within)).join(bases, ["length", "salt"])
        .withColumn("rank", F.col("base") + F.col("k") - 1)
    )
    found = spark.createDataFrame(
        intervals(plan(counts, capacity)),
        "to_length bigint, first bigint, after bigint, each bigint, bin bigint, at bigint",
    )
    on = (F.col("length") == F.col("to_length")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("after"))
    slot = F.col("rank") - F.col("first")
    return ranked.join(F.broadcast(found), on).select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("bin") + F.floor(slot / F.col("each"))).cast("bigint").alias("sequence_id"),
        (F.col("at") + F.pmod(slot, F.col("each")) * F.col("length")).cast("bigint").alias("offset"),
    )


def packed(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for each piece."""
    return pack(numbered(pieces(docs, tokenizer, capacity, end)), capacity)
