"""License scans by MinHash bands over overlapping windows.

A template is the set of its five-word shingles. Windows of each size in WINDOWS step by half their size, so a template of up to half a
window (one word more for the shortest) lies whole in one of them. A window's signature is BANDS minima, each a band of
its own; a template in the smallest window that can hold it is at least 0.15 of that window's shingles, so it is retrieved with probability
1 - 0.85**BANDS, over 0.9995. What is retrieved is verified: the exact share of the template's shingles in the window and its
neighbours must be THRESHOLD or more, over any span of the template's length. Templates are few and fixed, so their table travels with the tasks.

Defined cases: null or empty texts match nothing; a text under five words is one shingle; overlapping finds of one
template count once (as many as lie apart are kept); templates under five words aren't allowed; extra columns are dropped.
"""

from __future__ import annotations

import bisect
import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from evigraph.llm.common import documents
from evigraph.llm.hashing import U, mix, shingles, word_hashes

WORDS, THRESHOLD, BANDS = 5, 0.8, 48
WINDOWS = (10, 24, 64, 192, 512)
PART = 1 << 13

#: Notices of public licences.
TEMPLATES = {
    "MIT-notice": "Released under the MIT License.",
    "MIT-licensed": "Licensed under the MIT License.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "LGPL-3.0-notice": "This work is licensed under the GNU Lesser General Public License, version 3.",
    "AGPL-3.0-notice": "This work is licensed under the GNU Affero General Public License, version 3.",
    "CC-BY-4.0-notice": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0-notice": "Licensed under CC BY-SA 4.0.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-NC-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "BSD-2-Clause": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "BSD-3-Clause": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "Unlicense": "This is free and unencumbered software released into the public domain.",
}


def permuted(s: np.ndarray) -> np.ndarray:
    """One row a band: the shingle hashes under a permutation of 64-bit numbers (they are mixed already, so an odd factor is enough)."""
    k = mix(np.arange(1, BANDS + 1, dtype=U) * U(0xD6E8FEB86659FD93))
    return (s[None, :] ^ k[:, None]) * (k[:, None] | U(1))


def apart(shares: dict[int, float], width: int) -> list[tuple[int, float]]:
    """Of spans (start: share) of one width: as many as can lie without overlap, with the largest sum of shares, early ones first."""
    starts = sorted(shares)
    best: list[tuple[int, float, int]] = [(0, 0.0, len(starts))] * (len(starts) + 1)  # finds, sum, first one taken
    after = [bisect.bisect_left(starts, p + width) for p in starts]
    for k in range(len(starts) - 1, -1, -1):
        n, total, _ = best[after[k]]
        take = (n + 1, total + shares[starts[k]], k)
        best[k] = take if take[:2] >= best[k + 1][:2] else best[k + 1]
    out, k = [], 0
    while best[k][0]:
        k = best[k][2]
        out.append((starts[k], shares[starts[k]]))
        k = after[k]
    return out


class Scanner:
    def __init__(self, templates: dict[str, str]):
        self.names, self.sets, self.words = [], [], []
        self.by_window: dict[int, list[int]] = {}
        for name, text in sorted(templates.items()):
            w = word_hashes(text)
            if len(w) < WORDS:
                raise ValueError(f"{name} has fewer than {WORDS} words")
            size = next((x for x in WINDOWS if len(w) <= x // 2 + 1), None)
            if size is None:
                raise ValueError(f"{name} has more than {WINDOWS[-1] // 2 + 1} words; give it as parts")
            self.by_window.setdefault(size, []).append(len(self.names))
            self.names.append(name)
            self.words.append(len(w))
            self.sets.append(np.unique(shingles(w, WORDS)))
        self.minima = {size: np.stack([permuted(self.sets[t]).min(axis=1) for t in own], axis=1) for size, own in self.by_window.items()}

    def _retrieved(self, s: np.ndarray) -> set[tuple[int, int, int]]:
        """(window size, window number, template) whose signatures share a band; all bands of a piece are computed together."""
        hits: set[tuple[int, int, int]] = set()
        h = permuted(s)
        for size, own in self.by_window.items():
            half = np.minimum.reduceat(h, np.arange(0, len(s), size // 2), axis=1)
            least = half.copy()
            np.minimum(half[:, :-1], half[:, 1:], out=least[:, :-1])
            for k, t in enumerate(own):
                for i in np.flatnonzero((least == self.minima[size][:, k, None]).any(axis=0)):
                    hits.add((size, int(i), t))
        return hits

    def scan(self, text: str | None) -> list[tuple[str, int, int, float]]:
        """(template, first word, last word, containment) of each find, in order."""
        s = shingles(word_hashes(text or ""), WORDS)
        found: dict[tuple[int, int], float] = {}
        for at in range(0, len(s), PART):
            piece = s[at : at + PART + WINDOWS[-1]]
            for size, i, t in self._retrieved(piece):
                a = at + i * (size // 2)
                near = s[a : a + size + self.words[t]]
                inside = np.flatnonzero(np.isin(near, self.sets[t]))
                which = np.searchsorted(self.sets[t], near[inside])
                need = THRESHOLD * len(self.sets[t])
                if len(np.unique(which)) < need:
                    continue
                # A find may start at any template shingle of the window and lies within the template's length of it.
                ends = np.searchsorted(inside, inside + self.words[t])
                for k in range(int(np.searchsorted(inside, size))):
                    if (t, a + int(inside[k])) not in found and ends[k] - k >= need:
                        share = len(np.unique(which[k : ends[k]])) / len(self.sets[t])
                        if share >= THRESHOLD:
                            found[t, a + int(inside[k])] = share
        found = {(t, p): v for t in {t for t, _ in found} for p, v in apart({p: v for (u, p), v in found.items() if u == t}, self.words[t])}
        return sorted((self.names[t], p, p + self.words[t] - 1, v) for (t, p), v in found.items())


@functools.lru_cache(maxsize=4)
def _scanner(templates: tuple[tuple[str, str], ...]) -> Scanner:
    return Scanner(dict(templates))


FOUND = "array<struct<template:string,first_word:int,last_word:int,containment:double>>"


def scan_licenses(df: DataFrame, key: str = "doc_id", text: str = "text", templates: dict[str, str] | None = None) -> DataFrame:
    """One row a document: its finds in order, none for most."""
    fixed = tuple(sorted((templates or TEMPLATES).items()))
    kind = pa.list_(pa.struct([("template", pa.string()), ("first_word", pa.int32()), ("last_word", pa.int32()), ("containment", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = _scanner(fixed)
        for batch in batches:
            finds = [[{"template": n, "first_word": a, "last_word": z, "containment": v} for n, a, z, v in scanner.scan(t.as_py())] for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(finds, kind)], names=[key, "finds"])

    kind_of_key = df.schema[key].dataType.simpleString()
    return df.select(key, text).mapInArrow(run, f"`{key}` {kind_of_key}, finds {FOUND}")


def op6_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """License notices of every document."""
    return scan_licenses(documents(spark, sf_dir)).selectExpr("doc_id", "size(finds) AS n_finds", "array_distinct(transform(finds, f -> f.template)) AS templates", "finds")


QUERIES = {"op6_licenses": op6_licenses}
