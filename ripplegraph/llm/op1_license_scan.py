"""License scan: winnowed fingerprints pick candidate templates, banded alignment reports coverage and spans.

Texts and templates are read as lower-cased words of letters and digits. Hashes of 3-word grams are winnowed:
the smallest of each three in a row is a fingerprint, so any five words in common with a template share
one. The inverted index of the templates' fingerprints is fixed by the library and small (a few thousand
entries), and goes to every task. Where a text's fingerprints meet the index, hits of one template that lie
close together make a candidate region, whose diagonals differ by ``BAND`` at most, so a region is never longer
than its template and a few bands. The template is aligned with it within ``BAND`` words of the hits'
diagonals (longest common subsequence), and reported if ``COVERAGE`` of its words are matched there; of a
template of ``SHORT`` words or fewer all must be. After a report, what the region has left on both sides is
aligned again, so repeated notices are all found.
Of reports that overlap in a text, those with more matched words stay; ties go to the higher coverage, the shorter
span and the earlier template name.

Each row gives the span in words and in code points of the text, the matched words, and the coverage. Null and empty
texts have no matches. Ids may be null or repeat; extra columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm import kernel as K
from ripplegraph.llm.store import table, text_of

GRAM = 3
WINNOW = 3
BAND = 8
COVERAGE = 0.8
SHORT = 8

#: Notices and opening grants of public licenses.
TEMPLATES = {
    "AGPL-3.0-or-later": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "GPL-2.0-or-later": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0-or-later": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "LGPL-2.1-or-later": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "LGPL-3.0-or-later": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "MIT": "Released under the MIT License.",
    "MIT-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
}

#: ASCII bytes that are no letters or digits separate; bytes of longer characters belong to words.
SEPARATING = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])
_SCHEMA = "doc_id long, license string, coverage double, matched_words long, begin_word long, end_word long, begin_char long, end_char long"


def fingerprints(hashed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place, gram hash) of the winnowed grams of a sequence of word hashes."""
    gram = K.grams(hashed, GRAM)
    if len(gram) < WINNOW:
        return np.arange(len(gram)), gram
    bits = np.uint64((1 << len(gram).bit_length()) - 1)
    low = K.window_min((gram & ~bits) | np.arange(len(gram), dtype=np.uint64), WINNOW)
    at = np.unique((low & bits).astype(np.int64))
    return at, gram[at]


class TemplateIndex:
    """Inverted index from fingerprints to (template, place)."""

    def __init__(self, templates: dict[str, str]) -> None:
        self.names = sorted(templates)
        self.words: list[np.ndarray] = []
        postings: dict[int, list[tuple[int, int]]] = defaultdict(list)
        for t, name in enumerate(self.names):
            hashed = np.concatenate([w.hashes() for w in K.slices(pa.array([templates[name]]), lower=True, separating=SEPARATING)])
            self.words.append(hashed)
            for at, value in zip(*fingerprints(hashed), strict=True):
                postings[int(value)].append((t, int(at)))
        self.keys = np.array(sorted(postings), dtype=np.uint64)
        self.postings = [postings[int(k)] for k in self.keys]

    def hits(self, values: np.ndarray) -> np.ndarray:
        """Indices of ``values`` that are in the index."""
        at = np.minimum(np.searchsorted(self.keys, values), len(self.keys) - 1)
        return np.flatnonzero(self.keys[at] == values)

    def candidates(self, places: np.ndarray, values: np.ndarray) -> Iterator[tuple[int, list[tuple[int, int]]]]:
        """(template, hits (place, diagonal)) of groups of hits that lie close together."""
        by_template: dict[int, list[tuple[int, int]]] = defaultdict(list)
        for at, k in zip(places.tolist(), np.searchsorted(self.keys, values).tolist(), strict=True):
            for t, own in self.postings[k]:
                by_template[t].append((at, at - own))
        for t, found in by_template.items():
            found.sort(key=lambda x: (x[1], x[0]))
            first = 0
            for k in range(1, len(found)):
                if found[k][1] - found[first][1] > BAND:
                    yield t, found[first:k]
                    first = k
            yield t, found[first:]


def align(template: np.ndarray, text: np.ndarray, low: int, high: int) -> tuple[int, int, int]:
    """Longest common subsequence near diagonals low .. high: (matched, begin, end) in words of ``text``."""
    begin = max(low - BAND, 0)
    region = text[begin : high + BAND + len(template)]
    n, m = len(template), len(region)
    width = high - low + 2 * BAND + 1
    score = np.zeros((n + 1, m + 1), dtype=np.int32)
    for i in range(1, n + 1):
        a = max(1, i + low - begin - BAND)
        b = min(m, a + width)
        if a > m:
            break
        own = np.where(region[a - 1 : b] == template[i - 1], score[i - 1, a - 1 : b] + 1, score[i - 1, a : b + 1])
        own = np.maximum.accumulate(own)
        score[i, a : b + 1] = np.maximum(own, score[i, a - 1])
        score[i, b + 1 :] = score[i, b]
    i, j, first, last = n, int(np.searchsorted(score[n], score[n, m])), 0, 0  # the first end; from there the latest matches, so that the span is short
    while i and j and score[i, j]:
        if template[i - 1] == region[j - 1] and score[i, j] == score[i - 1, j - 1] + 1:
            last = last or j
            first = j
            i, j = i - 1, j - 1
        elif score[i, j] == score[i - 1, j]:
            i -= 1
        else:
            j -= 1
    return int(score[n, m]), begin + first - 1, begin + last


def scan(hashed: np.ndarray, index: TemplateIndex, coverage: float) -> list[tuple[int, int, int, int]]:
    """(template, matched, begin, end) of the licenses in one text; hits are known to exist."""
    places, values = fingerprints(hashed)
    hit = index.hits(values)
    found = []
    for t, hits in index.candidates(places[hit], values[hit]):
        open_parts = [(0, len(hashed), hits)]
        while open_parts:
            a, b, own = open_parts.pop()
            matched, begin, end = align(index.words[t], hashed[a:b], min(d for _, d in own) - a, max(d for _, d in own) - a)
            if matched >= (1.0 if len(index.words[t]) <= SHORT else coverage) * len(index.words[t]):
                begin, end = a + begin, a + end
                found.append((t, matched, begin, end))
                sides = (a, begin, [h for h in own if h[0] < begin]), (end, b, [h for h in own if h[0] >= end])
                open_parts += [side for side in sides if side[2]]
    kept: list[tuple[int, int, int, int]] = []
    begins: list[int] = []  # of ``kept``, which do not overlap and are in order
    for one in sorted(set(found), key=lambda x: (-x[1], len(index.words[x[0]]), x[3] - x[2], index.names[x[0]], x[2])):
        at = bisect_left(begins, one[2])
        if (at == 0 or kept[at - 1][3] <= one[2]) and (at == len(kept) or one[3] <= begins[at]):
            kept.insert(at, one)
            begins.insert(at, one[2])
    return kept


def _scanned(templates: dict[str, str], coverage: float):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = TemplateIndex(templates)
        for batch in batches:
            ids = batch.column("doc_id")
            out: list[tuple] = []
            for w in K.slices(batch.column("text"), lower=True, separating=SEPARATING):
                hashed = w.hashes()
                near = index.hits(K.grams(hashed, GRAM))
                for k in np.unique(w.doc[near]).tolist():
                    a, b = w.start[k], w.start[k + 1]
                    offset = int(w.offsets[k])
                    for t, matched, begin, end in scan(hashed[a:b], index, coverage):
                        at, to = int(w.begin[a + begin]), int(w.end[a + end - 1])
                        chars = [int(np.count_nonzero((w.data[offset:x] & 0xC0) != 0x80)) for x in (at, to)]
                        out.append((ids[w.first + k].as_py(), index.names[t], matched / len(index.words[t]), matched, begin, end, *chars))
            if out:
                kinds = [pa.int64(), pa.string(), pa.float64(), *[pa.int64()] * 5]
                yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out, strict=True), kinds, strict=True)], [x.split()[0] for x in _SCHEMA.split(", ")])

    return rows


def license_scan(docs: DataFrame, templates: dict[str, str] | None = None, coverage: float = COVERAGE) -> DataFrame:
    """One row per license found: doc_id, license, coverage, matched_words and the span in words and characters."""
    rows = docs.select(F.col("doc_id").cast("long"), text_of("text").alias("text"))
    return rows.mapInArrow(_scanned(templates or TEMPLATES, coverage), _SCHEMA)


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(table(spark, sf_dir, "documents"))
