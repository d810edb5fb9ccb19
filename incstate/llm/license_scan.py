"""License scans: MinHash bands over overlapping windows retrieve templates, exact containment verifies.

Every text is cut into overlapping windows of shingles, for each template length its own: windows of up to
32 shingles start at every word, longer ones at steps of a sixteenth to an eighth of their length, and they
are longer than the template by what a step can miss.  So a place where ``CONTAINED`` of a template's
shingles stand within its length lies whole in some window, whose Jaccard similarity with the template has
a known least value; rows per band and number of bands are set so that such a window shares a band with
the template with probability ``GUARANTEE``.  Only what the bands retrieve is verified: around a retrieved
window the template's shingles are counted exactly within its length from every word on, not within the
window.  Window minima come from doubling: one array of minima per power of two.
"""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import Ragged, bound_batches, flat, mix64, slices

WORDS = 5
CONTAINED = 0.8
GUARANTEE = 0.9999
BAND_ROWS = 2

#: License identifiers and the notices, headers and texts that announce them.
TEMPLATES = {
    "MIT": "Released under the MIT License.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted "
    "provided that the following conditions are met",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "CC-BY-4.0": "This work is licensed under the Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0 (long)": "This work is licensed under the Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-ND-4.0 (long)": "This work is licensed under the Creative Commons Attribution-NoDerivatives 4.0 International License.",
    "CC-BY-NC-4.0 (long)": "This work is licensed under the Creative Commons Attribution-NonCommercial 4.0 International License.",
    "CC-BY-NC-SA-4.0 (long)": "This work is licensed under the Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License.",
    "CC-BY-NC-ND-4.0 (long)": "This work is licensed under the Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License.",
    "CC-BY-4.0 (short)": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0.",
    "CC-BY-ND-4.0": "Licensed under CC BY-ND 4.0.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-NC-SA-4.0": "Licensed under CC BY-NC-SA 4.0.",
    "CC-BY-NC-ND-4.0": "Licensed under CC BY-NC-ND 4.0.",
    "MIT (text)": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated "
    'documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to '
    "use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the "
    "Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall "
    'be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, '
    "EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND "
    "NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER "
    "IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS "
    "IN THE SOFTWARE.",
    "ISC (text)": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, "
    "provided that the above copyright notice and this permission notice appear in all copies.",
    "Apache-2.0 (header)": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with '
    "the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or "
    'agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF '
    "ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "GPL-3.0 (header)": "under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License",
    "BSD-3-Clause (text)": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the "
    "following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the "
    "following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the "
    "following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright "
    "holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior "
    'written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, '
    "INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT "
    "SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES "
    "(INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) "
    "HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING "
    "IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "ISC (whole)": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided "
    'that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS '
    "ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE "
    "LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, "
    "WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS "
    "SOFTWARE.",
    "Zlib (text)": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any "
    "damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial "
    "applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be "
    "misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the "
    "product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be "
    "misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "BSL-1.0 (text)": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying "
    'documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software, and to '
    "prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following: "
    "The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following "
    "disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies "
    "or derivative works are solely in the form of machine-executable object code generated by a source language processor.",
    "Unlicense (text)": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, "
    "sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by "
    "any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in "
    "the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and "
    "successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software "
    "under copyright law.",
    "AGPL-3.0 (header)": "under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License",
    "LGPL-2.1 (header)": "under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License",
    "GPL-2.0 (header)": "under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License",
}


def identifier(name: str) -> str:
    """The license that a template announces; one has several templates, told apart in brackets."""
    return name.split(" (")[0]


_PACE = np.array([1, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3], np.uint64)


def _blank_table() -> bytes:
    return bytes(b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else b + 32 if 0x41 <= b <= 0x5A else 0x20 for b in range(256))


_BLANK = np.frombuffer(_blank_table(), np.uint8)


def normal(texts: pa.Array) -> pa.Array:
    """Texts in small ASCII letters with every other ASCII sign but digits as a blank."""
    texts = pc.fill_null(texts, "").cast(pa.large_string())
    bounds = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]]
    return pa.Array.from_buffers(pa.large_string(), len(texts), [None, pa.py_buffer((bounds - bounds[0]).tobytes()), pa.py_buffer(_BLANK[raw].tobytes())])


def word_shingles(texts: pa.Array):
    """Ragged words of normal texts and the hash of the ``WORDS`` words from each one (valid where ``ok``)."""
    r = Ragged(normal(texts))
    h = r.hashes()
    run = np.zeros(len(h), np.uint64)
    for j in range(WORDS):
        run[: max(0, len(h) - j)] += h[j:] * _PACE[j]
    ok = np.repeat(r.first[1:], r.counts) - np.arange(len(h)) >= WORDS
    return r, mix64(run), ok


class Bands(NamedTuple):
    """MinHash functions in bands of ``BAND_ROWS``."""

    factor: np.ndarray
    shift: np.ndarray

    def values(self, shingles: np.ndarray, band: int, row: int) -> np.ndarray:
        """One function's 32-bit values."""
        k = band * BAND_ROWS + row
        return (((shingles ^ self.shift[k]) * self.factor[k]) >> np.uint64(32)).astype(np.uint32)

    def __len__(self) -> int:
        return len(self.factor) // BAND_ROWS


class Windows(NamedTuple):
    """One window length with its step, and the templates (by number) that it retrieves."""

    length: int
    step: int
    templates: list[int]


class Index(NamedTuple):
    """Templates by number: distinct shingles and their extent in shingles; windows; bands and their values."""

    names: list[str]
    shingles: list[np.ndarray]
    sizes: list[int]
    windows: list[Windows]
    bands: Bands
    keys: np.ndarray


def window_of(size: int) -> tuple[int, int]:
    """Length and step of the windows for a template of ``size`` shingles."""
    step = 1 if size <= 32 else 1 << (size.bit_length() - 4)
    return -(-(size + step - 1) // step) * step, step


def build_index(templates: dict[str, str], contained: float = CONTAINED) -> Index:
    names, shingles, sizes = list(templates), [], []
    for name in names:
        _, run, ok = word_shingles(pa.array([templates[name]]))
        if not ok.any():
            raise ValueError(f"template {name} has fewer than {WORDS} words")
        shingles.append(np.unique(run[ok]))
        sizes.append(int(ok.sum()))
    # The least similarity of a template and a window around a place that holds enough of it.
    near = min(contained / (1 - contained + window_of(z)[0] / len(s)) for z, s in zip(sizes, shingles))
    count = max(4, math.ceil(math.log(1 - GUARANTEE) / math.log(1 - near**BAND_ROWS)))
    draw = np.random.default_rng(29)
    bands = Bands(
        draw.integers(0, 1 << 63, count * BAND_ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1),
        draw.integers(0, 1 << 63, count * BAND_ROWS, dtype=np.uint64),
    )
    keys = np.array([[[bands.values(s, b, k).min() for k in range(BAND_ROWS)] for b in range(count)] for s in shingles], np.uint32)
    held: dict[tuple[int, int], list[int]] = {}
    for t, z in enumerate(sizes):
        held.setdefault(window_of(z), []).append(t)
    return Index(names, shingles, sizes, [Windows(*w, t) for w, t in sorted(held.items())], bands, keys)


class _Minima:
    """Minima of one MinHash function over windows of some texts' shingles."""

    def __init__(self, value: np.ndarray, most: int):
        #: By power of two p, the least of the p values from each place on.
        self.levels = [value]
        while 2 << (len(self.levels) - 1) <= min(most, len(value)):
            last, p = self.levels[-1], 1 << (len(self.levels) - 1)
            self.levels.append(np.minimum(last[:-p], last[p:]))

    def all(self, length: int) -> np.ndarray:
        """Of each place the least of the next ``length`` values."""
        p = length.bit_length() - 1
        held = self.levels[p]
        ahead = length - (1 << p)
        return np.minimum(held[: len(held) - ahead], held[ahead:]) if ahead else held

    def at(self, starts: np.ndarray, length: int) -> np.ndarray:
        p = length.bit_length() - 1
        return np.minimum(self.levels[p][starts], self.levels[p][starts + length - (1 << p)])


def retrieved(run: np.ndarray, first: np.ndarray, many: np.ndarray, index: Index) -> list[tuple[int, int, int]]:
    """``(text, template, place)`` of windows that share a band with a template.

    Text d has ``many[d]`` shingles from ``first[d]`` on; windows don't reach over a text's end, where they are
    moved back to it, and a text shorter than a window is one window.
    """
    text = np.repeat(np.arange(len(many)), many)
    # The shingles alone, without the places that begin none.
    start = np.cumsum(many) - many
    run = run[np.repeat(first - start, many) + np.arange(len(text))]
    whole = np.flatnonzero(many)
    after = start + many
    grids = []
    for w in index.windows:
        long_ = np.flatnonzero(many >= w.length)
        if w.step == 1 or not len(long_):
            grids.append(None)
            continue
        count = (many[long_] - w.length) // w.step + 1
        nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        grids.append(np.concatenate((np.repeat(start[long_], count) + nth * w.step, after[long_] - w.length)))
    found: set[tuple[int, int, int]] = set()
    for b in range(len(index.bands)):
        minima, least = [], []
        for k in range(BAND_ROWS):
            value = index.bands.values(run, b, k)
            minima.append(_Minima(value, index.windows[-1].length))
            least.append(np.minimum.reduceat(value, start[whole]) if len(whole) else value)
        for w, grid in zip(index.windows, grids):
            short = many[whole] < w.length
            if grid is not None or (w.step == 1 and w.length <= len(run)):
                rows = [m.all(w.length) if grid is None else m.at(grid, w.length) for m in minima]
            else:
                rows = [run[:0].astype(np.uint32)] * BAND_ROWS
            for t in w.templates:
                key = index.keys[t, b]
                hit = np.flatnonzero(rows[0] == key[0])
                for k in range(1, BAND_ROWS):
                    hit = hit[rows[k][hit] == key[k]]
                place = hit if grid is None else grid[hit]
                place = place[place + w.length <= after[text[place]]]
                found.update((int(text[x]), t, int(x - start[text[x]])) for x in place)
                full = short.copy()
                for k in range(BAND_ROWS):
                    full &= least[k] == key[k]
                found.update((int(d), t, 0) for d in whole[full])
    return sorted(found)


def places(near: np.ndarray, size: int, mine: np.ndarray, contained: float) -> list[tuple[int, int]]:
    """Runs (first shingle, end) of ``near`` where ``size`` shingles hold enough of the distinct ones of a template."""
    spot = np.flatnonzero(np.isin(near, mine))
    which = np.searchsorted(mine, near[spot]).tolist()
    spot = spot.tolist()
    held: dict[int, int] = {}
    out: list[tuple[int, int]] = []
    stop = 0
    for k, x in enumerate(spot):
        while stop < len(spot) and spot[stop] < x + size:
            held[which[stop]] = held.get(which[stop], 0) + 1
            stop += 1
        if len(held) >= contained * len(mine) - 1e-9:
            if out and x <= out[-1][1]:
                out[-1] = out[-1][0], max(out[-1][1], spot[stop - 1] + 1)
            else:
                out.append((x, spot[stop - 1] + 1))
        held[which[k]] -= 1
        if not held[which[k]]:
            del held[which[k]]
    return out


def scan(texts: pa.Array, index: Index, contained: float = CONTAINED) -> list[list[tuple[str, int, int]]]:
    """For each text the (license, first word, words) of its verified places, overlapping ones merged."""
    r, run, _ = word_shingles(texts)
    many = np.maximum(r.counts - WORDS + 1, 0)
    out: list[list[tuple[str, int, int]]] = [[] for _ in range(r.n)]
    done: dict[tuple[int, int], int] = {}
    for d, t, place in retrieved(run, r.first[:-1], many, index):
        size = index.sizes[t]
        length = window_of(size)[0]
        # Everything that a place within the window can reach; what an earlier window settled is left out.
        low = max(0, place - size, done.get((d, t), 0))
        high = min(int(many[d]), place + length + size)
        if high <= done.get((d, t), 0):
            continue
        for x, y in places(run[r.first[d] + low : r.first[d] + high], size, index.shingles[t], contained):
            out[d].append((index.names[t], low + x, y - x + WORDS - 1))
        done[d, t] = place + length
    return [sorted(set(x)) for x in out]


def regions(found: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """The windows of :func:`scan` by license, overlapping ones of several templates merged."""
    out: list[tuple[str, int, int]] = []
    for name, first, words in sorted((identifier(n), x, w) for n, x, w in found):
        if out and out[-1][0] == name and first < out[-1][1] + out[-1][2]:
            _, x, w = out.pop()
            first, words = x, max(x + w, first + words) - x
        out.append((name, first, words))
    return out


def license_matches(docs: DataFrame, templates: dict[str, str] | None = None) -> DataFrame:
    """``docs(doc_id, text)`` to ``doc_id, n_matches, licenses, spans``, one row per input row.

    ``licenses`` lists the distinct identifiers found, in order, ``spans`` each verified region (license,
    first word, words), ``n_matches`` their number.  Null, empty and short texts match nothing; repeated
    rows and null ids are scanned like others; an empty table gives no rows; other columns are ignored.  A
    very long text is scanned as a whole, about 100 bytes of memory a word.  Templates are parameters of the
    job, a few hundred at most.
    """
    bound_batches(docs)
    index = build_index(templates or TEMPLATES)
    span = T.StructType().add("license", "string").add("first_word", "long").add("words", "long")

    @F.arrow_udf(T.ArrayType(span))
    def find(text: pa.Array) -> pa.Array:
        text = flat(text)
        kind = pa.list_(pa.struct([("license", pa.string()), ("first_word", pa.int64()), ("words", pa.int64())]))
        rows = [
            [{"license": n, "first_word": x, "words": w} for n, x, w in regions(found)] for a, b in slices(text) for found in scan(text[a:b], index)
        ]
        return pa.array(rows, kind)

    return docs.select("doc_id", find(F.coalesce("text", F.lit(""))).alias("spans")).select(
        "doc_id",
        F.size("spans").cast("long").alias("n_matches"),
        F.array_sort(F.array_distinct(F.col("spans.license"))).alias("licenses"),
        "spans",
    )


def license_digest(docs: DataFrame, templates: dict[str, str] | None = None) -> DataFrame:
    """``doc_id, n_licenses, licenses`` with the identifiers joined by commas."""
    return license_matches(docs, templates).select(
        "doc_id", F.size("licenses").cast("long").alias("n_licenses"), F.array_join("licenses", ",").alias("licenses")
    )
