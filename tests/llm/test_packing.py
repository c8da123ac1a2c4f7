"""Token ids against the tokenizer file on odd white space, and ranks of groups of any size."""

import random

import pytest

pytest.importorskip("hotgraph.llm")

from hotgraph.llm import packing  # noqa: E402
from hotgraph.llm.queries import tokenizer_path  # noqa: E402


@pytest.mark.parametrize("alphabet", ["ab \xa0\t\r\n　\x85", "aé1'.s \xa0\t\r\n　\x85\x1c\x0b\x0c ​  ﻿ßɏ́日"])
def test_ids_are_those_of_the_tokenizer_file(alphabet):
    encode, r = packing.Encoder(tokenizer_path()), random.Random(len(alphabet))
    for _ in range(50_000):
        text = "".join(r.choice(alphabet) for _ in range(r.randrange(12)))
        want = b"".join(i.to_bytes(4, "little") for i in encode.whole.encode(text, add_special_tokens=False).ids)
        assert encode(text) == want, repr(text)


@pytest.mark.parametrize(("group", "held"), [(None, 10**6), (7, 10**6), (7, 0)])
def test_repeated_rows_are_dealt_to_many_groups(spark, group, held):
    rows = [(None, None)] * 500 + [(1, "same words again")] * 300 + [(k, f"row {k} " * (k % 50)) for k in range(200)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(4)
    cut = packing.numbered(packing.pieces(docs, tokenizer_path()))
    out = packing.pack(cut, group=group, bases_held=held).collect()
    assert len(out) == cut.count()
    bins = {}
    for x in out:
        bins.setdefault(x.sequence_id, []).append((x.offset, x.length))
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 1024
    assert len(bins) == -(-sum(x.length for x in out) // 1024)
