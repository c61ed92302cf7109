"""License scan: MinHash bands over text windows retrieve templates, exact containment verifies."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import lean, ship

# Statements by which texts name their license, and well-known notices, as published.
TEMPLATES = {
    "AGPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "Apache-2.0": "you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "Apache-2.0-mention": "Licensed under the Apache License, Version 2.0.",
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "BSD-3-Clause": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "BSD-disclaimer": "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED.",
    "BSL-1.0": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so",
    "CC-BY-4.0-mention": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-NC-4.0-mention": "Licensed under CC BY-NC 4.0.",
    "CC-BY-NC-SA-4.0-mention": "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License.",
    "CC-BY-SA-4.0-mention": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC0-1.0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "EPL-2.0": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0",
    "GPL-2.0": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "GPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "GPL-3.0-mention": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "LGPL-2.1": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "LGPL-3.0": "This library is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "MIT-mention": "Released under the MIT License.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "WTFPL": "Everyone is permitted to copy and distribute verbatim or modified copies of this license document, and changing it is allowed as long as the name is changed.",
    "Zlib": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
}

SHINGLE = 2  # words; the shortest statements have five
BANDS, ROWS = 24, 2
#: At similarity s a window pairs with its template with probability 1 - (1 - s^ROWS)^BANDS. A stretch as
#: long as the template that holds a share c of its shingles lies at most an eighth of its length off a
#: window, which then has c - 1/8 of them in a row of equal size: s >= (c - 1/8) / (2 - c + 1/8), 0.509 for
#: c = 0.8, and the probability is 0.999 or more.


def _shingles(words: list[bytes]) -> np.ndarray:
    if not words:
        return np.zeros(0, dtype=np.uint64)
    codes = np.array([xxhash.xxh3_64_intdigest(w) for w in words], dtype=np.uint64)
    return _pairs(codes)


def _pairs(codes: np.ndarray) -> np.ndarray:
    out = codes.copy()[: max(1, len(codes) - SHINGLE + 1)]
    for j in range(1, min(SHINGLE, len(codes))):
        out = out * np.uint64(0x9E3779B97F4A7C15) + codes[j : j + len(out)]
    return out


def words_of(text: str) -> list[bytes]:
    return re.findall(r"[^\W_]+", text.lower())


class Scanner:
    def __init__(self, templates: dict[str, str], least: float):
        rng = np.random.default_rng(3)
        self.mul = rng.integers(1, 1 << 63, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
        self.add = rng.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)
        self.least = least
        self.names = sorted(templates)
        self.sets, self.sizes = [], []
        self.bands: dict[int, dict[int, list[int]]] = {}
        for i, name in enumerate(self.names):
            words = words_of(templates[name])
            sh = np.unique(_shingles([w.encode() for w in words]))
            self.sets.append(sh)
            self.sizes.append(len(words))
            table = self.bands.setdefault(len(words), {})
            for key in self.keys(self.minima(sh[None, :])[0]):
                table.setdefault(int(key), []).append(i)
        self.known = np.unique(np.concatenate(self.sets)) if self.sets else np.zeros(0, np.uint64)

    def minima(self, windows: np.ndarray) -> np.ndarray:
        return np.stack([((windows * m + a) >> np.uint64(8)).min(axis=1) for m, a in zip(self.mul, self.add)], axis=1)

    @staticmethod
    def keys(minima: np.ndarray) -> np.ndarray:
        m = minima.reshape(*minima.shape[:-1], BANDS, ROWS)
        out = np.arange(BANDS, dtype=np.uint64)
        for j in range(ROWS):
            out = (out ^ m[..., j]) * np.uint64(0xBF58476D1CE4E5B9)
        return out

    def scan(self, codes: np.ndarray) -> list[tuple[str, float, int, int]]:
        """(template, containment, first word, words): the best window of each stretch that holds
        at least the given share of a template's shingles.

        Windows have the template's length and start at every quarter length. Those without enough
        shingles known to any template cannot hold one and are passed over before hashing. Of
        templates found in one place (versions of a license share most words) the best match counts.
        """
        sh = _pairs(codes) if len(codes) else np.zeros(0, np.uint64)
        known = np.isin(sh, self.known)
        found = []
        if not known.any():
            return found
        seen = np.concatenate(([0], np.cumsum(known)))
        for size, table in self.bands.items():
            span = max(1, size - SHINGLE + 1)
            if seen[-1] < self.least * span / 2:
                continue
            step = max(1, span // 4)
            starts = np.arange(0, max(1, len(sh) - span + 1), step)
            if len(sh) > span and starts[-1] != len(sh) - span:
                starts = np.append(starts, len(sh) - span)
            stop = np.minimum(starts + span, len(sh))
            starts = starts[seen[stop] - seen[starts] >= max(1, self.least * span / 2)]
            if not len(starts):
                continue
            windows = sh[np.minimum(starts[:, None] + np.arange(span), len(sh) - 1)]
            for start, keys in zip(starts.tolist(), self.keys(self.minima(windows))):
                for i in {i for key in keys.tolist() for i in table.get(key, ())}:
                    lo, hi = max(0, start - span // 2), start + span + span // 2  # the stretch around the window
                    near = np.flatnonzero(np.isin(sh[lo:hi], self.sets[i])) + lo
                    share = len(np.unique(sh[near])) / len(self.sets[i])
                    if share >= self.least:
                        found.append((self.names[i], share, int(near[0]), int(near[-1]) - int(near[0]) + SHINGLE))
        best: list[tuple] = []
        for one in sorted(set(found), key=lambda x: (-x[1], -x[3], x[2], x[0])):
            if all(min(one[2] + one[3], o[2] + o[3]) - max(one[2], o[2]) <= min(one[3], o[3]) / 2 for o in best):
                best.append(one)
        return sorted(best, key=lambda x: (x[2], x[0]))


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, least: float = 0.8) -> DataFrame:
    """doc_id, n_hits, licenses (names), hits (name, containment, first_word, n_words): one row per
    input row. Null and empty texts hold none; repeated rows are scanned each; only doc_id and text
    are read. Whole texts are scanned, however long, in windows of each template's length. An empty
    table gives no row."""
    templates = TEMPLATES if templates is None else templates

    def run(batches):
        scanner, cache = Scanner(templates, least), {}
        for batch in batches:
            hits = []
            for text in batch.column(1).to_pylist():
                codes = []
                for w in words_of(text or ""):
                    c = cache.get(w)
                    if c is None:
                        if len(cache) > 100_000:
                            cache.clear()
                        c = cache[w] = xxhash.xxh3_64_intdigest(w.encode())
                    codes.append(c)
                hits.append([{"license": n, "containment": s, "first_word": a, "n_words": b} for n, s, a, b in scanner.scan(np.array(codes, dtype=np.uint64))])
            kind = pa.list_(pa.struct([("license", pa.string()), ("containment", pa.float64()), ("first_word", pa.int64()), ("n_words", pa.int64())]))
            yield pa.record_batch([batch.column(0), pa.array([len(h) for h in hits], pa.int64()), pa.array(hits, kind)], names=["doc_id", "n_hits", "hits"])

    shape = "doc_id long, n_hits long, hits array<struct<license: string, containment: double, first_word: long, n_words: long>>"
    out = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lean(run), shape)
    return out.select("doc_id", "n_hits", F.array_join(F.array_sort(F.array_distinct("hits.license")), ",").alias("licenses"), "hits")


ship(__name__)
