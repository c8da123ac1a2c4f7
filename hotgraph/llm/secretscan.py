"""Secret scan: Aho-Corasick keyword prefilter, anchored expressions near hits, checksum validation.

Two automata run over each whole text. One holds the keywords of every kind over the text with A-Z lower-cased.
The other holds one key, a run of `HEX_RUN` class marks, over the text with every character of 0-9a-f replaced by
the mark: it finds where long hexadecimal runs are. Only at those places is an expression tried, anchored there,
so the text is never searched by an expression. Base kinds (assign, access, hex) follow the fixed grammar below.
The method adds kinds that carry their own check: tokens that end in a CRC-32 of their body (ghtoken, npmtoken),
JSON web tokens whose header decodes (jwt), and PEM blocks whose DER length agrees with their body (pem). Of these added
kinds, what is longer than the format's use allows is not taken for a key: a web token's header or signature of over
4,096 characters or payload of over 65,536, a PEM body of over 65,536 (white space counted). That bounds the work at
each hit in hostile texts; base kinds have no such limit.

A null text counts as empty. Offsets are code points, end exclusive. Repeated rows give one row each. Only
doc_id and text are read, so clashing names of other columns do no harm.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re
import zlib
from collections.abc import Iterable, Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, prepare, rows

#: Kinds in the order used for ties, the grammar of the base kinds, and their least lengths.
KINDS = ("assign", "access", "hex", "ghtoken", "npmtoken", "jwt", "pem")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
ASSIGN_LEAST, ACCESS_LEAST, HEX_RUN = 8, 16, 32

GITHUB = re.compile(r"gh[pousr]_([0-9A-Za-z]{30})([0-9A-Za-z]{6})(?![0-9A-Za-z])")
NPM = re.compile(r"npm_([0-9A-Za-z]{30})([0-9A-Za-z]{6})(?![0-9A-Za-z])")
JWT = re.compile(r"(eyJ[A-Za-z0-9_-]{8,4096})\.(eyJ[A-Za-z0-9_-]{2,65536})\.([A-Za-z0-9_-]{16,4096})(?![A-Za-z0-9_-])")
PEM = re.compile(r"-----BEGIN ((?:[A-Z]+ )?PRIVATE KEY)-----\s*([A-Za-z0-9+/=\s]{16,65536}?)\s*-----END \1-----")
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"

_HEX_TABLE = bytes(0x01 if c in b"0123456789abcdef" else 0x20 for c in range(128)) + bytes([0x20] * 128)
_LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
_ARROW = pa.schema([
    ("doc_id", pa.int64()),
    ("spans", pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))),
])
SCHEMA = "doc_id bigint, spans array<struct<kind: string, start: bigint, end: bigint>>"


def crc_base62(body: str) -> str:
    """CRC-32 of the body in six base-62 digits, as such tokens carry it at their end."""
    n, out = zlib.crc32(body.encode()), ""
    for _ in range(6):
        n, k = divmod(n, 62)
        out = BASE62[k] + out
    return out


def _summed(m: re.Match) -> bool:
    return crc_base62(m[1]) == m[2]


def _decoded(m: re.Match) -> bool:
    try:
        return "alg" in json.loads(base64.urlsafe_b64decode(m[1] + "=" * (-len(m[1]) % 4)))
    except (ValueError, TypeError, RecursionError):
        return False


def _der(m: re.Match) -> bool:
    """A DER sequence: tag 0x30, and a length that agrees with the bytes there are."""
    try:
        raw = base64.b64decode("".join(m[2].split()), validate=True)
    except binascii.Error:
        return False
    if len(raw) < 2 or raw[0] != 0x30:
        return False
    if raw[1] < 0x80:
        return raw[1] == len(raw) - 2
    k = raw[1] & 0x7F
    return 0 < k < 9 and int.from_bytes(raw[2 : 2 + k], "big") == len(raw) - 2 - k


#: keyword in lower case: (kind, expression anchored at the keyword, test of the match)
RULES = {
    **{w: ("assign", ASSIGN, lambda m: len(m[2]) >= ASSIGN_LEAST) for w in ("password", "passwd", "secret", "token", "api_key", "apikey")},
    "akia": ("access", ACCESS, lambda m: len(m[0]) >= ACCESS_LEAST),
    **{f"gh{k}_": ("ghtoken", GITHUB, _summed) for k in "pousr"},
    "npm_": ("npmtoken", NPM, _summed),
    "eyj": ("jwt", JWT, _decoded),
    "-----begin": ("pem", PEM, _der),
}


def keywords() -> tuple[ahocorasick.Automaton, ahocorasick.Automaton]:
    words, runs = ahocorasick.Automaton(), ahocorasick.Automaton()
    for w in RULES:
        words.add_word(w, w)
    runs.add_word("\x01" * HEX_RUN, HEX_RUN)
    words.make_automaton()
    runs.make_automaton()
    return words, runs


def find(text: str | None, trees: tuple[ahocorasick.Automaton, ahocorasick.Automaton]) -> list[tuple[int, int, int]]:
    """(start, number of the kind, end) of every span, sorted. Within a kind matches are leftmost and disjoint.

    A match that fails its test still takes its characters, as it would when searching from left to right.
    """
    if not text:
        return []
    words, runs = trees
    low = text.lower() if text.isascii() else text.translate(_LOWER) if len(text) < 64 else text.encode().lower().decode()
    hits = sorted((end - len(w) + 1, w) for end, w in words.iter(low))
    taken, out = dict.fromkeys(KINDS, 0), []
    for at, w in hits:
        kind, pattern, good = RULES[w]
        if at >= taken[kind] and (m := pattern.match(text, at)):
            if good(m) or kind in KINDS[:3]:
                taken[kind] = m.end()
            if good(m):
                out.append((m.start(), KINDS.index(kind), m.end()))
    marks, done = text.encode("ascii", "replace").translate(_HEX_TABLE).decode("ascii"), 0
    for end, n in runs.iter(marks):
        if end >= done:
            at = end - n + 1
            done = HEX.match(text, at).end()
            out.append((at, 2, done))
    return sorted(out)


def secrets(docs: DataFrame) -> DataFrame:
    """One row for each document: SCHEMA, spans by start, then by kind in the order of KINDS."""
    prepare(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees = keywords()
        found = (
            (doc, [{"kind": KINDS[k], "start": a, "end": b} for a, k, b in find(text, trees)])
            for doc, text in rows(batches)
        )
        yield from emit(found, _ARROW)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(run, SCHEMA)


def digest(found: DataFrame) -> DataFrame:
    """The columns of the query's contract, from secrets()'s rows."""
    of = lambda *kinds: F.filter("spans", lambda s: s.kind.isin(*kinds))
    joined = lambda spans: F.array_join(
        F.transform(spans, lambda s: F.concat_ws(":", s.kind, s.start.cast("string"), s.end.cast("string"))), ","
    )
    return found.select(
        "doc_id", *(F.size(of(k)).cast("bigint").alias(f"n_{k}") for k in KINDS[:3]),
        F.sha2(joined(of(*KINDS[:3])).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"),
    )


def sha256_of(spans: list[tuple[int, int, int]]) -> str:
    return hashlib.sha256(",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans if k < 3).encode()).hexdigest()
