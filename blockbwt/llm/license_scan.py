"""Operator 5: license scans by MinHash over overlapping windows.

A text's 5-word shingles (ASCII letters lowered, ends of words stripped of
punctuation, words of punctuation alone left out) are cut into blocks, and every few blocks in a row are a window; a
template of t shingles is looked for in windows of 1.25 t shingles and one block
more, of the largest power of two that a quarter of t holds, so an occurrence
that edits stretch by a quarter lies in a window whole. A block's minima are
those of the two half as large, so one pass over the shingles serves templates of
all sizes. A window whose BANDS bands of one row share one with a template is its
candidate; the window's full shingles then decide: the share of the template's
that it contains is at least CONTAINED.

At that containment the Jaccard coefficient is at least 0.75 / (1 + 1.5 - 0.75)
= 0.43, so a window is missed with probability (1 - 0.43) ** 24 = 1.4e-6, and an
occurrence lies in one window or more. Texts are read whole, window by window.

Templates are a table of the user's (TEMPLATES by default), of a checked size.

Defined results: null and empty texts match nothing; a template of fewer than
five words is one shingle and is found by runs of as many words; equal templates
are each reported; rows that repeat are each reported; an empty table or an
empty template list gives no row.
"""

from __future__ import annotations


import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WORDS, CONTAINED, BANDS, MOST_TEMPLATE_BYTES = 5, 0.75, 24, 64 << 20

#: Whole short licenses, and of long ones the notice that they ask files to carry.
TEMPLATES = {
    "mit-notice": "Released under the MIT License.",
    "apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "gpl-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "cc-by-nc-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "cc-by-4.0-notice": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc-by-sa-4.0-notice": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "cc-by-nc-sa-4.0-notice": "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License.",
    "cc0-1.0-notice": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "mit-whole": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "bsd-2-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd-3-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "boost-1.0": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:",
    "unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "apache-2.0": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "gpl-2.0": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "gpl-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "lgpl-2.1": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "agpl-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "epl-2.0": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/",
}
_SEEDS = np.random.default_rng(70_007)
_FACTORS = (_SEEDS.integers(0, 1 << 32, BANDS, dtype=np.uint32) | 1).astype(np.uint32)
_ADDENDS = _SEEDS.integers(0, 1 << 32, BANDS, dtype=np.uint32)
_EDGES = b"\"'`.,:;!?()[]{}<>*#-_/\\|"
_STORE = 400_000
_NOTHING = np.uint64(xxhash.xxh3_64_intdigest(b""))


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = value = xxhash.xxh3_64_intdigest(word.strip(_EDGES))
        return value


def _words(text: str | None, hashes: dict) -> tuple[np.ndarray, np.ndarray]:
    """The words' hashes and their places among all words; comment marks and other words of punctuation alone are none."""
    words = (text or "").encode().lower().split()
    found = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    places = np.flatnonzero(found != _NOTHING)
    return found[places], places


def _runs(words: np.ndarray, k: int) -> np.ndarray:
    """The hash of every run of k words, in order."""
    if len(words) < k or not k:
        return np.zeros(0, np.uint64)
    out = np.full(len(words) - k + 1, np.uint64(k))
    for i in range(k):
        out = (out ^ words[i : len(words) - k + 1 + i]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return out


class Library:
    """Templates by the words of a shingle: (name, set, level, blocks in a window) each, a level's blocks having 2 ** level shingles."""

    def __init__(self, templates: dict[str, str]):
        if sum(len(x.encode()) for x in templates.values()) > MOST_TEMPLATE_BYTES:
            raise ValueError(f"templates of more than {MOST_TEMPLATE_BYTES} bytes; scan them in portions")
        hashes, self.kinds = _Hashes(), {}
        for name, text in templates.items():
            words, _ = _words(text, hashes)
            if not len(words):
                continue
            k = min(WORDS, len(words))
            own = np.unique(_runs(words, k))
            level = max(1, len(own) // 4).bit_length() - 1
            self.kinds.setdefault(k, []).append((name, own, level, self.blocks(len(own), 1 << level)))

    @staticmethod
    def blocks(shingles: int, block: int) -> int:
        """Blocks in a window for a template of so many shingles."""
        return -(-int(1.25 * shingles + 0.999) // block) + 1


def _signed(shingles: np.ndarray, band: int) -> np.ndarray:
    return (shingles >> np.uint64(32)).astype(np.uint32) * _FACTORS[band] ^ _ADDENDS[band]


def _levels(lens: np.ndarray, most: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each level where its blocks begin among the blocks of the level below (of level 0: the shingles), and where each text's blocks begin."""
    out, below = [], lens
    for level in range(most + 1):
        own = -(-lens // (1 << level))
        begins = np.cumsum(own) - own
        if level:
            first = np.cumsum(below) - below
            number = np.arange(int(own.sum())) - np.repeat(begins, own)
            out.append((np.repeat(first, own) + 2 * number, begins))
        else:
            out.append((np.arange(int(own.sum())), begins))
        below = own
    return out


def scan_texts(texts: list[str | None], library: Library, hashes: dict, use_bands: bool = True) -> list[tuple[int, str, float, int]]:
    """(index, template, containment, first word of the window) of each text's best window. Without use_bands every window is checked."""
    words, places = zip(*(_words(x, hashes) for x in texts)) if texts else ((), ())
    best: dict[tuple[int, str], tuple[float, int]] = {}
    for k, templates in library.kinds.items():
        runs = [_runs(x, k) for x in words]
        has = [i for i, x in enumerate(runs) if len(x)]
        if not has:
            continue
        all_runs = np.concatenate([runs[i] for i in has])
        lens = np.array([len(runs[i]) for i in has])
        offsets = np.cumsum(lens) - lens
        levels = _levels(lens, max(x[2] for x in templates))
        wanted = set()

        def window(level: int, block: int, wide: int) -> tuple[int, int, int]:
            """Of the window that begins at a block: its text, and its shingles from and to."""
            text = int(np.searchsorted(levels[level][1], block, side="right")) - 1
            first = (block - int(levels[level][1][text])) << level
            return text, first, min(first + (wide << level), int(lens[text]))

        if use_bands:
            for band in range(BANDS):
                low = _signed(all_runs, band)
                for level, (starts, begins) in enumerate(levels):
                    if level:
                        low = np.minimum.reduceat(low, starts)
                    some = [(t, np.uint32(_signed(x[1], band).min()), x[3]) for t, x in enumerate(templates) if x[2] == level]
                    if not some:
                        continue
                    table = np.zeros(1 << 16, bool)
                    table[[int(m) & 0xFFFF for _, m, _ in some]] = True
                    at = np.flatnonzero(table[(low & np.uint32(0xFFFF)).astype(np.uint16)])
                    # a window's minimum is a template's only where one of its blocks has it
                    for i in at.tolist():
                        for t, m, wide in some:
                            if low[i] == m:
                                text = int(np.searchsorted(begins, i, side="right")) - 1
                                end = int(begins[text + 1]) if text + 1 < len(begins) else len(low)
                                for b in range(max(i - wide + 1, int(begins[text])), i + 1):
                                    if low[b : min(b + wide, end)].min() == m:
                                        wanted.add((b, t))
        else:
            wanted = {(b, t) for t, x in enumerate(templates) for b in range(len(levels[x[2]][0]))}
        for b, t in sorted(wanted):
            name, own, level, wide = templates[t]
            text, first, stop = window(level, b, wide)
            share = float(np.isin(own, all_runs[offsets[text] + first : offsets[text] + stop]).mean())
            key = (has[text], name)
            if share >= CONTAINED and (key not in best or (-share, first) < (-best[key][0], best[key][1])):
                best[key] = (share, first)
    return [(i, name, share, int(places[i][place])) for (i, name), (share, place) in sorted(best.items())]


def scan(df: DataFrame, templates: dict[str, str] | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, license, containment, first_word): each document's matches, at their best window."""
    given = TEMPLATES if templates is None else templates
    sent = df.sparkSession.sparkContext.broadcast(Library(given))

    def run(batches):
        hashes = _Hashes()
        for batch in batches:
            ids, texts, at = batch.column(0).to_pylist(), batch.column(1), 0
            while at < len(ids):
                some, size, begin = [], 0, at
                while at < len(ids) and size < 1 << 20:
                    some.append(texts[at].as_py())
                    size += len(some[-1] or "")
                    at += 1
                if len(hashes) > _STORE:
                    hashes = _Hashes()
                found = scan_texts(some, sent.value, hashes)
                yield pa.RecordBatch.from_arrays([pa.array([ids[begin + x[0]] for x in found], pa.int64()), pa.array([x[1] for x in found], pa.string()), pa.array([x[2] for x in found], pa.float64()), pa.array([x[3] for x in found], pa.int64())], names=["doc_id", "license", "containment", "first_word"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, license string, containment double, first_word long")


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(common.table(spark, sf_dir, "documents"))
