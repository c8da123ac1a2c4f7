"""License scan: Dice coefficient over word bigrams against licence templates, with size bounds that prune.

Units of a text are its windows of words, across line breaks and inside lines. A text is normalised (words of letters,
digits and non-ASCII characters, A-Z lower-cased, version numbers reduced to their first number) and the multiset of word
bigrams of a window is compared with each template's: Dice = 2 |A and B| / (|A| + |B|). As the overlap is at most the
smaller size, a window can reach the threshold t for a template of b bigrams only with b t / (2 - t) to b (2 - t) / t of
them, and at least b t / (2 - t) shared ones: templates that share fewer with the whole text are pruned, and so are
starts with fewer in reach. The closest window begins and ends with a shared bigram, so all others are passed over. Of
windows that overlap the closest counts for one template, and between templates the one with most shared bigrams, so
a notice inside a whole licence is not found again. The templates are fixed and few, so they travel in code.

A null or empty text has no units and no licence. Repeated rows are reported each. Only doc_id and text are read.
"""

from __future__ import annotations

import re
from bisect import bisect
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotgraph.llm.common import emit, prepare, rows
from hotgraph.llm.decontaminate import normal_words
from hotgraph.llm.licensetexts import FULL_TEXTS

THRESHOLD = 0.8

#: Forms of a short notice, and the names that licences go by in one.
_NOTICES = ("Licensed under {}.", "Released under {}.", "This work is licensed under {}.", "This project is licensed under {}.")
_NAMED = {
    "MIT": "the MIT License",
    "Apache-2.0": "the Apache License, Version 2.0",
    "GPL-2.0": "the GNU General Public License, version 2", "GPL-3.0": "the GNU General Public License, version 3",
    "LGPL-2.1": "the GNU Lesser General Public License, version 2.1", "LGPL-3.0": "the GNU Lesser General Public License, version 3",
    "AGPL-3.0": "the GNU Affero General Public License, version 3",
    "BSD-2-Clause": "the BSD 2-Clause License", "BSD-3-Clause": "the BSD 3-Clause License", "LicenseRef-BSD": "the BSD License",
    "MPL-2.0": "the Mozilla Public License, Version 2.0", "EPL-2.0": "the Eclipse Public License, Version 2.0", "ISC": "the ISC License",
    "CC0-1.0": "CC0 1.0", "CC-BY-4.0": "CC BY 4.0", "CC-BY-SA-4.0": "CC BY-SA 4.0", "CC-BY-NC-4.0": "CC BY-NC 4.0", "CC-BY-ND-4.0": "CC BY-ND 4.0",
}
#: Standard headers and short texts.
_FREE = (
    "This program is free software: you can redistribute it and/or modify it under the terms of the GNU {}General Public License "
    "as published by the Free Software Foundation, either version {} of the License, or (at your option) any later version."
)
_HEADERS = {
    "MIT": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    ),
    "GPL-2.0": (_FREE.format("", 2),), "GPL-3.0": (_FREE.format("", 3),), "LGPL-2.1": (_FREE.format("Lesser ", 2.1),), "LGPL-3.0": (_FREE.format("Lesser ", 3),),
    "AGPL-3.0": (_FREE.format("Affero ", 3),),
    "LicenseRef-BSD": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
    "CC-BY-4.0": ("This work is licensed under a Creative Commons Attribution 4.0 International License.",),
    "CC-BY-SA-4.0": ("This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",),
    "CC-BY-NC-4.0": ("This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",),
    "CC-BY-ND-4.0": ("This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License.",),
    "CC0-1.0": ("To the extent possible under law, the author has waived all copyright and related rights to this work.",),
    "ISC": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    "Unlicense": (
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    ),
    "LicenseRef-all-rights-reserved": ("All rights reserved.",),
}
#: Which of the whole texts is which.
_WHOLE = {
    "MIT": ("MIT",), "Apache-2.0": ("Apache-2.0",), "GPL": ("GPL-1.0", "GPL-2.0", "GPL-3.0"), "LGPL": ("LGPL-2.0", "LGPL-2.1", "LGPL-3.0"),
    "BSD": ("BSD-3-Clause", "BSD-2-Clause"), "MPL-2.0": ("MPL-2.0",), "CC0": ("CC0-1.0",),
}

#: Templates by SPDX identifier, with a LicenseRef where SPDX has none: whole texts, and notices and headers.
WHOLE = {name: (text,) for family, names in _WHOLE.items() for name, text in zip(names, FULL_TEXTS[family], strict=True)}
TEMPLATES = {
    name: (*_HEADERS.get(name, ()), *(f.format(_NAMED[name]) for f in _NOTICES if name in _NAMED))
    for name in dict.fromkeys([*_NAMED, *_HEADERS, *WHOLE])
}

SCHEMA = "doc_id bigint, found array<struct<license: string, line: int, dice: double>>"
_ARROW = pa.schema([
    ("doc_id", pa.int64()),
    ("found", pa.list_(pa.struct([("license", pa.string()), ("line", pa.int32()), ("dice", pa.float64())]))),
])


def words_of(text: str) -> list[bytes]:
    return normal_words(re.sub(r"(\d+)(?:\.\d+)+", r"\1", text))


def bigrams(text: str) -> Counter:
    words = words_of(text)
    return Counter(zip(words, words[1:], strict=False))


def dice(a: Counter, b: Counter) -> float:
    total = a.total() + b.total()
    return 2 * sum((a & b).values()) / total if total else 0.0


class Templates:
    """Templates by size and by bigram."""

    def __init__(self, threshold: float) -> None:
        self.threshold = threshold
        self.all = [(name, bigrams(t)) for name, texts in TEMPLATES.items() for t in (*texts, *WHOLE.get(name, ()))]
        self.by: dict[tuple, list[int]] = defaultdict(list)
        for k, (_, b) in enumerate(self.all):
            for g in b:
                self.by[g].append(k)
        sizes = [b.total() for _, b in self.all]
        self.place = {g: k for k, g in enumerate(self.by)}
        #: How often each template holds each bigram, and the least overlap and the largest window of each template.
        self.counts = np.zeros((len(self.place), len(self.all)), np.int32)
        for k, (_, b) in enumerate(self.all):
            self.counts[[self.place[g] for g in b], k] = list(b.values())
        self.need = np.ceil(np.array(sizes) * threshold / (2 - threshold) - 1e-9).astype(np.int64)
        self.reach = np.floor(np.array(sizes) * (2 - threshold) / threshold + 1e-9).astype(np.int64)
        self.least = min(sizes) * threshold / (2 - threshold) - 1e-9
        self.most = max(sizes) * (2 - threshold) / threshold + 1e-9

    def best(self, unit: Counter) -> tuple[float, str] | None:
        """The closest template at or above the threshold; of equals the first by name."""
        n = unit.total()
        if not self.least <= n <= self.most:
            return None
        low, high = n * self.threshold / (2 - self.threshold) - 1e-9, n * (2 - self.threshold) / self.threshold + 1e-9
        near = {k for g in unit for k in self.by.get(g, ()) if low <= self.all[k][1].total() <= high}
        found = [(-d, self.all[k][0]) for k in near if (d := dice(unit, self.all[k][1])) >= self.threshold]
        return (-min(found)[0], min(found)[1]) if found else None


    def windows(self, k: int, at: np.ndarray, gram: np.ndarray) -> list[tuple[int, float, int, int]]:
        """(overlap, Dice, first and last bigram) of the windows that reach the threshold for template k, none overlapping.

        at, gram: places in the text of the bigrams that any template holds, and which they are.
        """
        own = self.counts[gram, k] > 0
        at, gram = at[own], gram[own]
        kinds, gram = np.unique(gram, return_inverse=True)
        most, size = self.counts[kinds, k], self.all[k][1].total()
        order = np.argsort(gram, kind="stable")
        first = np.searchsorted(gram[order], np.arange(len(kinds)))
        turn = np.empty(len(gram), np.int64)  # how often the bigram came before in the text
        turn[order] = np.arange(len(gram)) - first[gram[order]]
        end = np.searchsorted(at, at + self.reach[k])
        before, last, found = np.zeros(len(kinds), np.int64), 0, []
        for i in np.flatnonzero(end - np.arange(len(at)) >= self.need[k]).tolist():
            before += np.bincount(gram[last:i], minlength=len(kinds))
            last, here = i, slice(i, end[i])
            both = np.cumsum(turn[here] - before[gram[here]] < most[gram[here]])
            d = 2 * both / (size + at[here] - at[i] + 1)
            if d[j := int(d.argmax())] >= self.threshold:
                found.append((int(both[j]), float(d[j]), int(at[i]), int(at[i + j])))
        return apart(sorted(found, key=lambda w: (-w[1], -w[0], w[2])))


def apart(found: list[tuple]) -> list[tuple]:
    """Those of the windows (.., .., first, last, ..) that share no bigram with an earlier one of the list."""
    first, out = [], []
    for w in found:
        k = bisect(first, (w[2],))
        if (k == 0 or first[k - 1][1] < w[2]) and (k == len(first) or first[k][0] > w[3]):
            first.insert(k, (w[2], w[3]))
            out.append(w)
    return out


def find(text: str | None, templates: Templates) -> list[tuple[str, int, float]]:
    """(licence, line on which its window begins, Dice) in the order of the text."""
    words = words_of(text or "")
    place = templates.place.get
    gram = np.array([place(g, -1) for g in zip(words, words[1:], strict=False)], np.int64)
    at = np.flatnonzero(gram >= 0)
    gram = gram[at]
    kinds, often = np.unique(gram, return_counts=True)
    shared = np.minimum(templates.counts[kinds], often[:, None]).sum(0)
    found = [
        (*w, templates.all[k][0]) for k in np.flatnonzero(shared >= templates.need).tolist() for w in templates.windows(k, at, gram)
    ]
    if not found:
        return []
    ends = np.cumsum([len(words_of(line)) for line in text.split("\n")])
    best = sorted(apart(sorted(found, key=lambda w: (-w[0], -w[1], w[4], w[2]))), key=lambda w: w[2])
    return [(name, int(np.searchsorted(ends, start, side="right")), d) for _, d, start, _, name in best]


def licenses(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """SCHEMA for each document: the licences found, in the order of the text."""
    prepare(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = Templates(threshold)
        each = ((doc, [{"license": a, "line": k, "dice": d} for a, k, d in find(text, t)]) for doc, text in rows(batches))
        yield from emit(each, _ARROW)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(run, SCHEMA)


def digest(found: DataFrame) -> DataFrame:
    """doc_id, n_found, licenses (sorted, each once, joined by commas), best_dice."""
    return found.select(
        "doc_id", F.size("found").cast("bigint").alias("n_found"),
        F.array_join(F.array_sort(F.array_distinct(F.col("found.license"))), ",").alias("licenses"),
        F.array_max(F.col("found.dice")).alias("best_dice"),
    )
