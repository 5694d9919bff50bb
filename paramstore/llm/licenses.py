"""License scans: MinHash bands over overlapping text windows retrieve templates, exact shingle containment verifies them.

A template is a named text. Its word shingles (five words; a shorter template is one shingle) give a MinHash signature of `bands` x
`rows` values; each band is a key of a table from which windows retrieve templates. For each class of template lengths (up to n = 8,
16, 32, ... words) a text is cut into windows of 2n words, half overlapping, so that any occurrence of up to n words lies whole in a
window. Of a window only shingles that some template has are taken: others can be in no match, and without them similarities only
rise. A window that holds the share c of a template's m shingles has at most 2n - 4 shingles, so its Jaccard similarity is at least
c * m / (2n - 4 + (1 - c) * m), which for c = 0.8 and m > n / 2 - 4 is above 0.17 from 16 words on. With one row a band and 64 bands it
retrieves its template with a probability of 1 - 0.83 ** 64 = 0.99999 at that worst case. Candidates are verified by exact containment: the share of the template's
different shingles in the window, at least 0.8, which defines a match. Templates of one or two shingles are looked up as they are, with certainty.

The templates are broadcast; they are a parameter with a bound on their words (`most_words`). Words: runs of letters, digits and
non-ASCII characters, A-Z in lower case. Nulls: a null text has no words. Rows are kept one for one. Empty tables or an empty list of
templates give rows without matches.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paramstore.llm.common import Held, per_batch, raw_texts, texts_of
from paramstore.llm.decontaminate import FACTOR, window_hashes, words_of

SHINGLE = 5

#: Public license texts and notices, as they stand in files.
TEMPLATES = {
    "apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "mit-line": "Released under the MIT License.",
    "gpl-3-line": "This work is licensed under the GNU General Public License, version 3.",
    "cc-by-nc-4.0-line": "Licensed under CC BY-NC 4.0.",
    "all-rights-reserved-line": "All rights reserved.",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "bsd-2": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "bsd-3": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "bsd-conditions": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "gpl-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "lgpl-notice": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "all-rights-reserved": "All rights reserved. No part of this publication may be reproduced without permission.",
}


def mixed(h: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """64-bit permutations of h, one for each seed."""
    with np.errstate(over="ignore"):
        h = (h ^ seeds) * FACTOR
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        return h ^ (h >> np.uint64(29))


class Templates:
    """Shingles, signatures and bands of the templates."""

    def __init__(self, texts: dict[str, str], shingle: int, bands: int, rows: int):
        self.shingle, self.bands, self.rows = shingle, bands, rows
        with np.errstate(over="ignore"):
            self.seeds = np.arange(1, bands * rows + 1, dtype=np.uint64) * np.uint64(0x632BE59BD9B4E019)
        self.ids: dict[bytes, int] = {}
        self.names, self.shingles, self.lengths = [], [], []
        short: dict[tuple[int, ...], list[int]] = defaultdict(list)
        by_length: dict[int, list[int]] = defaultdict(list)
        for name in sorted(texts):
            words = [self.ids.setdefault(w, len(self.ids) + 1) for w in words_of(texts[name].encode())]
            if not words:
                continue
            k = len(self.names)
            self.names.append(name)
            size = min(shingle, len(words))
            own = {tuple(words[i : i + size]) for i in range(len(words) - size + 1)}
            self.shingles.append(own)
            self.lengths.append(len(words))
            if len(own) <= 2:
                short[size].append(k)
            else:
                by_length[1 << (len(words) - 1).bit_length()].append(k)
        self.short = dict(short)
        self.classes = {n: (own, self._table(own)) for n, own in by_length.items()}
        long = [window_hashes(np.array(x, np.uint64), shingle) for own, _ in self.classes.values() for k in own for x in self.shingles[k]]
        self.all = np.unique(np.concatenate(long)) if long else np.zeros(0, np.uint64)

    def bands_of(self, h: np.ndarray) -> list[int]:
        """Keys of the bands of a set of shingle hashes."""
        low = mixed(h[:, None], self.seeds[None, :]).min(axis=0).reshape(self.bands, self.rows).tolist()
        return [hash((b, *x)) for b, x in enumerate(low)]

    def _table(self, own: list[int]) -> dict[int, list[int]]:
        table: dict[int, list[int]] = defaultdict(list)
        for k in own:
            h = np.unique(np.concatenate([window_hashes(np.array(s, np.uint64), self.shingle) for s in self.shingles[k]]))
            for key in self.bands_of(h):
                table[key].append(k)
        return dict(table)

    def scan(self, words: list[bytes], least: float) -> dict[int, tuple[float, int, int]]:
        """Best containment, and its word range, of each template found."""
        get = self.ids.get
        ids = np.array([get(w, 0) for w in words], np.uint64)
        found: dict[int, tuple[float, int, int]] = {}
        known = np.concatenate(([0], np.cumsum(ids != 0)))

        def keep(k: int, share: float, a: int, b: int) -> None:
            if share >= least and share > found.get(k, (0.0,))[0]:
                found[k] = (share, a, b)

        for size, own in self.short.items():  # one or two shingles: looked up as they are
            whole = np.flatnonzero(known[size:] - known[:-size] == size) if len(ids) >= size else np.zeros(0, np.int64)
            for i in whole.tolist():
                part = tuple(ids[i : i + size].tolist())
                for k in own:
                    if part in self.shingles[k]:
                        a, b = i, min(i + self.lengths[k], len(ids))
                        near = {tuple(ids[j : j + size].tolist()) for j in range(max(0, i - 1), min(i + 2, len(ids) - size + 1))}
                        keep(k, len(near & self.shingles[k]) / len(self.shingles[k]), a, b)
        size = self.shingle
        whole = np.flatnonzero(known[size:] - known[:-size] == size) if len(ids) >= size else np.zeros(0, np.int64)
        h = window_hashes(ids, size, whole)
        at = np.minimum(np.searchsorted(self.all, h), max(len(self.all) - 1, 0))
        own_ = self.all[at] == h if len(self.all) else np.zeros(len(h), bool)
        places, h = whole[own_], h[own_]  # the text's shingles that some template has
        if not len(places):
            return found
        for n, (_, table) in self.classes.items():
            block = places // n
            for w in np.unique(np.concatenate((block, np.maximum(block - 1, 0)))).tolist():
                inside = slice(int(np.searchsorted(places, w * n)), int(np.searchsorted(places, (w + 2) * n - size + 1)))
                if inside.start == inside.stop:
                    continue
                met = {k for key in self.bands_of(np.unique(h[inside])) for k in table.get(key, ())}
                if met:
                    held = {tuple(ids[i : i + size].tolist()): i for i in reversed(places[inside].tolist())}
                    for k in met:
                        hits = [held[s] for s in self.shingles[k] if s in held]
                        if hits:
                            keep(k, len(hits) / len(self.shingles[k]), min(hits), max(hits) + size)
        return found


def _templates(payload) -> Templates:
    return Templates(*payload)


def scan(docs: DataFrame, templates: dict[str, str] | None = None, least: float = 0.8, shingle: int = SHINGLE, bands: int = 64, rows: int = 1, id_col: str = "doc_id", text_col: str = "text", most_words: int = 2_000_000) -> DataFrame:
    """doc_id, n_words, n_licenses, licenses (names, sorted), matches (name, containment, word range) of every row of docs."""
    texts = TEMPLATES if templates is None else templates
    if sum(len(words_of(t.encode())) for t in texts.values()) > most_words:
        raise ValueError(f"templates of more than most_words={most_words} words")
    source = texts_of(docs, id_col, text_col)
    held = docs.sparkSession.sparkContext.broadcast(Held(_templates, (texts, shingle, bands, rows)))
    kind = source.schema["doc_id"].dataType.simpleString()
    shape = pa.list_(pa.struct([("name", pa.string()), ("containment", pa.float64()), ("start", pa.int64()), ("end", pa.int64())]))

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        known, n, names, matches = held.value.get(), [], [], []
        for raw in raw_texts(batch.column(1)):
            words = words_of(raw)
            found = sorted((known.names[k], *v) for k, v in known.scan(words, least).items()) if known.names and words else []
            n.append(len(words))
            names.append([m[0] for m in found])
            matches.append([dict(zip(("name", "containment", "start", "end"), m, strict=True)) for m in found])
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array([len(x) for x in names], pa.int64()), pa.array(names, pa.list_(pa.string())), pa.array(matches, shape)], ["doc_id", "n_words", "n_licenses", "licenses", "matches"])

    return source.mapInArrow(per_batch(kernel), f"doc_id {kind}, n_words long, n_licenses long, licenses array<string>, matches array<struct<name:string,containment:double,start:long,end:long>>")


def containing(docs: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """Count of documents by license name, for a report."""
    return scan(docs, text_col=text_col, **options).select(F.explode("licenses").alias("license")).groupBy("license").agg(F.count("*").alias("documents"))
