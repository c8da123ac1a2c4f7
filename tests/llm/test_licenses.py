"""Licences inside longer texts: wrapped, in the middle of a line, and whole."""

import random
import textwrap

import pytest

pytest.importorskip("hotgraph.llm")

from hotgraph.llm import licenses as x  # noqa: E402

T = x.Templates(0.8)
PROSE = "The mill stood by a slow river for many years before anyone thought of mending its old wheel again"


def named(text):
    return [name for name, _, _ in x.find(text, T)]


def test_wrapped_paragraphs_in_longer_texts():
    for name, at in (("MIT", 0), ("GPL-3.0", 0), ("GPL-2.0", 0), ("LicenseRef-BSD", 0), ("Apache-2.0", 0), ("ISC", 1), ("Unlicense", 0)):
        for width in (40, 72):
            text = f"{PROSE}\n\n{textwrap.fill(x.TEMPLATES[name][at], width, break_long_words=False, break_on_hyphens=False)}\n\n{PROSE}"
            assert x.find(text, T) == [(name, 2, 1.0)]


def test_notice_inside_a_line():
    assert x.find(f"{PROSE}. Released under the MIT License. {PROSE}.", T) == [("MIT", 0, 1.0)]
    assert named(f"{PROSE}. All rights reserved. {PROSE}. Licensed under CC BY 4.0. {PROSE}") == ["LicenseRef-all-rights-reserved", "CC-BY-4.0"]


def test_whole_texts():
    for name, texts in x.WHOLE.items():
        for text in texts:
            found = x.find(f"{PROSE}\n{text}{PROSE}", T)
            assert [(n, k) for n, k, _ in found] == [(name, 1)] and found[0][2] > 0.99
    assert named(PROSE) == [] and x.find(None, T) == x.find("", T) == x.find("license", T) == []


def test_source_headers_and_versions():
    for mark in ("# ", " * ", "// ", "-- ", "; ", "%% "):
        lines = textwrap.wrap(x.TEMPLATES["LGPL-3.0"][0], 60)
        text = "\n".join(["#!/bin/sh", *(mark + line for line in lines), "", "int main() { return 0; }"])
        assert x.find(text, T) == [("LGPL-3.0", 1, 1.0)]
    for name in ("GPL-2.0", "GPL-3.0", "BSD-2-Clause", "BSD-3-Clause", "AGPL-3.0", "EPL-2.0", "ISC"):
        assert named(f"{PROSE}. Licensed under {x._NAMED[name]}. {PROSE}") == [name]


def test_ties_and_long_lines():
    notice = "All rights reserved."
    assert named(f"{notice} {notice}\n{notice}") == ["LicenseRef-all-rights-reserved"] * 3
    line = " ".join([PROSE] * 2000)
    assert [(n, k) for n, k, _ in x.find(f"{line} Released under the MIT License. {line}", T)] == [("MIT", 0)]


def test_against_all_windows():
    r = random.Random(3)
    pool = " ".join(t for n in ("MIT", "GPL-3.0", "CC-BY-4.0", "LicenseRef-all-rights-reserved") for t in x.TEMPLATES[n][-3:]).split()
    for _ in range(40):
        words = [r.choice(pool) for _ in range(12)] + r.choice(x.TEMPLATES["GPL-3.0"][1:4]).split() + [r.choice(pool) for _ in range(9)]
        del words[r.randrange(len(words))]
        text = " ".join(words)
        w = x.words_of(text)
        spans = [x.bigrams(b" ".join(w[i:j]).decode()) for i in range(len(w)) for j in range(i + 2, len(w) + 1)]
        short = [k for k, (_, b) in enumerate(T.all) if b.total() < 60]
        for k in short:
            best = max(x.dice(s, T.all[k][1]) for s in spans)
            grams = list(zip(w, w[1:], strict=False))
            at = x.np.array([i for i, g in enumerate(grams) if g in T.place])
            got = T.windows(k, at, x.np.array([T.place[grams[i]] for i in at]))
            assert [round(got[0][1], 9)] == [round(best, 9)] if best >= 0.8 else not got
