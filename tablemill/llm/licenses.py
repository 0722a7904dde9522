"""License scans: MinHash bands over overlapping windows, then exact containment.

Every template is the set of its word shingles (five words, or all words of a
shorter notice). A text is cut into windows of two strides of shingles, one
stride apart; the stride is a size class not below the template's number of
shingles, so a copy always lies in one window. Every window carries one MinHash
value a band; a window whose value equals a template's in any band is a
candidate. The number of bands follows from the least similarity that a window
with 0.8 of a template can have, so that fewer than one in ``1 / MISS`` is
missed. Candidates are settled by exact shingle containment within the text:
the largest share of a template's shingles inside any run of two strides.

Defined results: null and empty texts match nothing; repeated rows each report;
ties of containment go to the earliest place.
"""

from __future__ import annotations

import re
from math import ceil, log

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablemill.llm.common import columns, lean
from tablemill.llm.language import texts_words
from tablemill.llm.pieces import slices

WORDS = 5
LEAST = 0.8
MISS = 1e-6

# Texts of widely used license notices.
TEMPLATES = {
    "all-rights-reserved": "All rights reserved.",
    "apache-2.0-short": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0. Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "bsd-redistribution": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "cc-by-nc-4.0-short": "Licensed under CC BY-NC 4.0.",
    "gpl-3.0-short": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "isc-permission": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "mit-permission": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "mit-short": "Released under the MIT License.",
    "mpl-2.0-header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
}


def word_key(word: str) -> int:
    """A word without case and outer punctuation; one that is all punctuation is not a word (0)."""
    bare = re.sub(r"^[^\w]+|[^\w]+$", "", word.lower())
    return (xxhash.xxh64_intdigest(bare) or 1) if bare else 0


def shingle_hashes(keys: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of n word keys."""
    count = len(keys) - n + 1
    h = np.full(max(0, count), n, np.uint64)
    for i in range(n):
        if count > 0:
            h = (h ^ keys[i : i + count]) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(32)
    return h


def permutations(bands: int) -> tuple[np.ndarray, np.ndarray]:
    draw = [xxhash.xxh64_intdigest(f"band-{i}") for i in range(2 * bands)]
    return np.array(draw[:bands], np.uint64) | np.uint64(1), np.array(draw[bands:], np.uint64)


def permuted(h: np.ndarray, a: np.uint64, b: np.uint64) -> np.ndarray:
    x = (h ^ b) * a
    return x ^ (x >> np.uint64(31))


class Library:
    """Templates by size class: (shingle words, stride) to bands, band tables and exact shingle sets."""

    def __init__(self, templates: dict[str, str], words: int = WORDS, least: float = LEAST, miss: float = MISS):
        self.names = sorted(templates)
        self.least = least
        self.classes: dict[tuple[int, int], dict] = {}
        for number, name in enumerate(self.names):
            keys = np.array([k for w in templates[name].split() if (k := word_key(w))], np.uint64)
            if not len(keys):
                continue
            n = min(words, len(keys))
            shingles = np.unique(shingle_hashes(keys, n))
            m = len(keys) - n + 1
            stride = 1 if m == 1 else 1 << (m - 1).bit_length()
            self.classes.setdefault((n, stride), {"templates": []})["templates"].append((number, shingles))
        for (n, stride), c in self.classes.items():
            window = stride * (2 if stride > 1 else 1)
            m = min(len(s) for _, s in c["templates"])
            similarity = min(1.0, ceil(least * m) / (window + m - ceil(least * m)))
            bands = 1 if similarity >= 1 else ceil(log(miss) / log(1 - similarity))
            c |= {"bands": bands, "window": window, "hashes": permutations(bands)}
            c["minima"] = [np.array([permuted(s, a, b).min() for _, s in c["templates"]], np.uint64) for a, b in zip(*c["hashes"])]

    def candidates(self, c: dict, h: np.ndarray, first: np.ndarray, size: np.ndarray, stride: int) -> set[tuple[int, int]]:
        """(text, template place) pairs that share a band value in some window; h: the shingles of all texts in a row."""
        strides = -(-size // stride)
        of = np.repeat(np.arange(len(size)), strides)
        starts = np.repeat(first, strides) + (np.arange(len(of)) - np.repeat(np.cumsum(strides) - strides, strides)) * stride
        last = np.concatenate([of[1:] != of[:-1], [True]])
        found: set[tuple[int, int]] = set()
        for a, b, minima in zip(*c["hashes"], c["minima"]):
            low = np.minimum.reduceat(permuted(h, a, b), starts)
            if c["window"] > stride:
                low = np.where(last, low, np.minimum(low, np.concatenate([low[1:], low[-1:]])))
            hit = np.flatnonzero(np.isin(low, minima))
            for w in hit.tolist():
                found.update((int(of[w]), t) for t in np.flatnonzero(minima == low[w]).tolist())
        return found

    def scan(self, keys: np.ndarray, counts: np.ndarray) -> list[tuple[int, int, float, int]]:
        """(text, template, containment, first word) of texts given as one row of word keys."""
        out = []
        ends = np.cumsum(counts)
        for (n, stride), c in self.classes.items():
            size = np.maximum(0, counts - n + 1)
            all_h = shingle_hashes(keys, n)
            if not len(all_h) or not size.any():
                continue
            at = np.repeat(ends - counts, size) + np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
            h = all_h[at]
            first = np.cumsum(size) - size
            some = size > 0
            back = np.flatnonzero(some)
            for text, t in sorted(self.candidates(c, h, first[some], size[some], stride)):
                text = int(back[text])
                number, shingles = c["templates"][t]
                share, place = containment(h[first[text] : first[text] + size[text]], shingles, c["window"])
                if share >= self.least:
                    out.append((text, number, share, place))
        return out


def containment(h: np.ndarray, shingles: np.ndarray, window: int) -> tuple[float, int]:
    """Largest share of distinct ``shingles`` within a run of ``window`` shingles of a text, and where it begins."""
    where = np.flatnonzero(np.isin(h, shingles))
    which = np.searchsorted(shingles, h[where])
    best, place, held, low = 0, 0, np.zeros(len(shingles), np.int64), 0
    kinds = 0
    for high in range(len(where)):
        held[which[high]] += 1
        kinds += held[which[high]] == 1
        while where[high] - where[low] >= window:
            held[which[low]] -= 1
            kinds -= held[which[low]] == 0
            low += 1
        if kinds > best:
            best, place = kinds, int(where[low])
    return float(best / len(shingles)), place


def scanned(docs: DataFrame, templates: dict[str, str] | None = None, text: str = "text", doc_id: str = "doc_id", least: float = LEAST) -> DataFrame:
    """doc_id, license, containment, first_word: one row for each text and template found in it."""
    given = TEMPLATES if templates is None else templates
    returns = "doc_id long, license string, containment double, first_word long"
    shape = columns(returns)

    def run(batches):
        library = Library(given, least=least)
        for b in batches:
            for part in slices(b, 1):
                pool, index, counts = texts_words(part.column(1))
                key = np.fromiter(map(word_key, pool.to_pylist()), np.uint64, len(pool))
                keys = key[index]
                real = keys != 0
                per = np.bincount(np.repeat(np.arange(len(counts)), counts)[real], minlength=len(counts))
                rows = library.scan(keys[real], per)
                ids = part.column(0).to_pylist()
                yield pa.RecordBatch.from_arrays([pa.array([ids[r[0]] for r in rows], pa.int64()), pa.array([library.names[r[1]] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.float64()), pa.array([r[3] for r in rows], pa.int64())], schema=shape)

    return docs.select(F.col(doc_id).cast("long"), F.col(text)).mapInArrow(lean(run), returns)


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scanned(spark.read.parquet(f"{sf_dir}/documents.parquet"))
