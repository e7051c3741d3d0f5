"""License scan: MinHash bands over overlapping text windows retrieve templates; exact shingle containment verifies them.

Templates of about equal length form a class with windows of its own: blocks of half a template, enough blocks that some window
holds any full copy. From the least Jaccard similarity that a copy of ``least`` containment then has to its window, the number
of bands follows that finds it with probability ``1 - MISS`` at least. A band hit is verified on the window and its neighbours:
the share of the template's shingles found there. Of the windows that pass, runs that touch make one match with the best share.

Words are runs of letters and digits in either case: punctuation, quotes and comment signs ('#', '//', '*', '--' and the like)
part words and are no words, in templates and texts. Comment signs of letters (REM, dnl) are words. Reported positions count
white-space words. A short notice inside a match of the fuller template of its license (X-notice in X) is not reported again.

Edge cases: null, empty and short texts match nothing; long texts are scanned whole; repeated rows give equal rows; an empty
table gives no rows; other columns are ignored. Templates of fewer words than a shingle are refused.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from distds.llm import textkernels as tk
from distds.llm.scratch import only

#: Common public license notices.
TEMPLATES = {
    "MIT-notice": "Released under the MIT License.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "BSD": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "GPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "MIT-warranty": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "Apache-2.0-warranty": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "BSD-conditions": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "BSD-3-clause": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "BSD-warranty": "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES",
    "GPL-warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "LGPL-2.1": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "zlib": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "BSL-1.0": "Distributed under the Boost Software License, Version 1.0.",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-NC-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
}
#: Further passages that occur in whole licenses only.
REST = {
    "ISC-warranty": "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "zlib-head": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.",
    "zlib-conditions": "1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "Unlicense-dedication": "In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.",
}
#: Whole license texts (without their copyright lines) by passages.
WHOLE = {
    "MIT-whole": ("MIT", "MIT-warranty"),
    "BSD-2-whole": ("BSD", "BSD-conditions", "BSD-warranty"),
    "BSD-3-whole": ("BSD", "BSD-conditions", "BSD-3-clause", "BSD-warranty"),
    "ISC-whole": ("ISC", "ISC-warranty"),
    "zlib-whole": ("zlib-head", "zlib", "zlib-conditions"),
    "Unlicense-whole": ("Unlicense", "Unlicense-dedication"),
}
TEMPLATES |= {name: " ".join((TEMPLATES | REST)[p] for p in parts) for name, parts in WHOLE.items()}
WORDS, LEAST, MISS = 5, 0.8, 1e-3
#: Rows of a band.
ROWS = 2
OUT = "doc_id long, template string, first_word int, last_word int, share double"


#: Bytes of words: ASCII letters and digits, and what stands beyond ASCII.
PLAIN = np.array([b >= 128 or chr(b).isalnum() for b in range(256)])


def plain_words(run: list[bytes]):
    """(hashes of all words, words before each text, white-space word of its text that each lies in)."""
    data, wide, _, wide_cuts = tk.words(run)
    gap = ~PLAIN[data]
    for lead, size in ((data[:-1] == 0xC2, 2), ((data[:-1] == 0xE2) & (data[1:] == 0x80), 3)):  # U+0080 to U+00BF, U+2000 to U+203F: signs, quotes, dashes
        for j in range(size):
            gap[np.flatnonzero(lead) + j] = True
    edge = np.diff(np.concatenate(([True], gap)).astype(np.int8))
    starts, ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    cuts = np.searchsorted(starts, np.cumsum([0] + [len(b) + 1 for b in run]))
    inside = np.searchsorted(wide, starts, "right") - 1 - np.repeat(wide_cuts[:-1], np.diff(cuts))
    return tk.word_hashes(data, starts, ends), cuts, inside


def permuted(s: np.ndarray, i: int) -> np.ndarray:
    return (s ^ tk.mix64(np.array([i + 1], np.uint64))) * (tk.mix64(np.array([i + 7919], np.uint64)) | np.uint64(1))


class LengthClass:
    """Templates whose shingle counts lie within a factor two, with their windows and bands."""

    def __init__(self, sets: dict[str, np.ndarray], k_least: float, miss: float):
        sizes = [len(s) for s in sets.values()]
        self.sets, small, large = sets, min(sizes), max(sizes)
        self.block = max(1, small // 2)
        self.blocks = -(-(large + self.block - 1) // self.block)
        width = self.block * self.blocks
        common = np.ceil(k_least * small)
        self.least = common / (width + small - common) if width > 1 else 1.0
        self.bands = max(1, int(np.ceil(np.log(miss) / np.log(1 - min(self.least**ROWS, 0.9999)))))
        table: list[dict[int, list[str]]] = [{} for _ in range(self.bands)]
        for name, s in sets.items():
            for b in range(self.bands):
                table[b].setdefault(int(self.band(np.array([permuted(s, b * ROWS + r).min() for r in range(ROWS)]).reshape(ROWS, 1), b)[0]), []).append(name)
        self.table = table
        self.keys = [np.sort(np.array(list(t), dtype=np.uint64)) for t in table]

    @staticmethod
    def band(minima: np.ndarray, b: int) -> np.ndarray:
        out = np.full(minima.shape[1], np.uint64(b + 1))
        for row in minima:
            out = tk.mix64(out * tk.STEP + row)
        return out

    def hits(self, s: np.ndarray):
        """(window, template) of band hits over the shingles of many texts in a row; window w starts at block w."""
        starts = np.arange(0, len(s), self.block)
        found = set()
        for b in range(self.bands):
            minima = []
            for r in range(ROWS):
                low = np.minimum.reduceat(permuted(s, b * ROWS + r), starts)
                wide = low
                for j in range(1, self.blocks):
                    wide = np.minimum(wide, np.append(low[j:], np.full(min(j, len(low)), np.uint64(2**64 - 1))))
                minima.append(wide)
            sig = self.band(np.stack(minima), b)
            keys = self.keys[b]
            at = np.minimum(np.searchsorted(keys, sig), len(keys) - 1)
            for w in np.flatnonzero(keys[at] == sig):
                found.update((int(w), t) for t in self.table[b][int(sig[w])])
        return found


def classes(templates: dict[str, str], k: int, least: float, miss: float) -> list[LengthClass]:
    sets = {}
    for name, text in templates.items():
        h, _, _ = plain_words([text.encode()])
        if len(h) < k:
            raise ValueError(f"template {name} has fewer than {k} words")
        sets[name] = np.unique(tk.shingle_hashes(h, k))
    by: dict[int, dict] = {}
    for name, s in sets.items():
        by.setdefault(int(np.log2(len(s))), {})[name] = s
    return [LengthClass(x, least, miss) for x in by.values()]


def matches(run: list[bytes], groups: list[LengthClass], k: int, least: float):
    """(text, template, first word, last word, share) for a run of texts."""
    h, cuts, inside = plain_words(run)
    whole = [tk.shingle_hashes(h[cuts[i] : cuts[i + 1]], k) if cuts[i + 1] - cuts[i] >= k else np.zeros(0, np.uint64) for i in range(len(run))]
    s = np.concatenate(whole)
    if not len(s):
        return []
    offs = np.cumsum([0] + [len(x) for x in whole])
    raw = []
    for g in groups:
        for w, name in g.hits(s):
            lo, hi = (w - 1) * g.block, (w + g.blocks + 1) * g.block
            t = g.sets[name]
            for d in range(np.searchsorted(offs, max(lo, 0), "right") - 1, np.searchsorted(offs, min(hi, len(s)), "left")):
                a, b = max(lo, offs[d]), min(hi, offs[d + 1])
                at = np.flatnonzero(np.isin(s[a:b], t))
                share = len(np.unique(s[a:b][at])) / len(t) if len(at) else 0.0
                if share >= least:
                    raw.append((int(d), name, int(a - offs[d] + at[0]), int(a - offs[d] + at[-1] + k - 1), share))
    out = []
    for d, name, a, b, share in sorted(set(raw)):
        if out and out[-1][:2] == [d, name] and a <= out[-1][3]:
            out[-1][3], out[-1][4] = max(b, out[-1][3]), max(share, out[-1][4])
        else:
            out.append([d, name, a, b, share])
    full = {(d, name): [] for d, name, *_ in out}
    for d, name, a, b, _ in out:
        full[d, name].append((a, b))
    own = [m for m in out if not any(a <= m[2] and m[3] <= b for a, b in full.get((m[0], m[1].removesuffix("-notice")), ()) if m[1].endswith("-notice"))]
    return [(d, name, int(inside[cuts[d] + a]), int(inside[cuts[d] + b]), share) for d, name, a, b, share in own]


def scan(batches, templates: dict[str, str], k: int, least: float, miss: float):
    groups = classes(templates, k, least, miss)
    for batch in batches:
        ids, rows = batch.column("doc_id").to_pylist(), []
        for first, run in tk.runs_of(batch.column("text")):
            rows += [(ids[first + d], *rest) for d, *rest in matches(run, groups, k, least)]
        cols = list(zip(*rows)) if rows else [[]] * 5
        kinds = (pa.int64(), pa.string(), pa.int32(), pa.int32(), pa.float64())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["doc_id", "template", "first_word", "last_word", "share"])


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, k: int = WORDS, least: float = LEAST, miss: float = MISS) -> DataFrame:
    """One row for each match: doc_id, template, first and last word, and the share of the template's shingles found."""
    templates = TEMPLATES if templates is None else templates
    return only(docs, "doc_id", "text").mapInArrow(lambda it: scan(it, templates, k, least, miss), OUT)
