"""Licences of files: headers and whole texts by TF-IDF cosine to templates, the rest from the nearest licence file above.

Every line of every file is compared with the templates, by its words weighted
by how rare they are in the whole corpus; long lines count as several, and
neighbouring lines that each look somewhat like a template are compared once
more as one block. Whole files are compared with whole licence texts. A file
that is little else than a notice, whose whole text is that of a licence, or
that is named like one, is the licence file of its directory; files without a
notice inherit from the nearest directory above that has one.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cityweave.llm.decontam import BETWEEN
from cityweave.llm.kernel import Words, blocks, buffers, mapped

# Notices and opening words of common licences.
TEMPLATES = {
    "MIT": ("Released under the MIT License.", "MIT License. Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction"),
    "Apache-2.0": ("Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0; you may not use this file except in compliance with the License. Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS"),
    "BSD-3-Clause": ("Use of this source code is governed by a BSD style license that can be found in the LICENSE file.", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    "GPL-3.0": ("This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version"),
    "GPL-2.0": ("Licensed under the GNU General Public License, version 2.",),
    "LGPL-3.0": ("Licensed under the GNU Lesser General Public License, version 3.",),
    "AGPL-3.0": ("Licensed under the GNU Affero General Public License, version 3.",),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "CC0-1.0": ("Dedicated to the public domain under CC0 1.0 Universal.",),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
    "proprietary": ("Copyright. All rights reserved.", "Proprietary and confidential. Unauthorized copying of this file is strictly prohibited."),
}

# Whole texts of short licences, without names of holders.
FULL = {
    "MIT": "MIT License Copyright (c) Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "BSD-3-Clause": "Copyright (c). All rights reserved. Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS ``AS IS'' AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "BSD-2-Clause": "Copyright (c). All rights reserved. Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS ``AS IS'' AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. For more information, please refer to <http://unlicense.org/>",
}

FULL |= {
    "ISC": "ISC License Copyright (c) Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "Zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
}

# Long licences open with their titles, here as terms.
TITLES = {
    "gnu affero general public license version 3": "AGPL-3.0",
    "gnu lesser general public license version 3": "LGPL-3.0",
    "gnu general public license version 3": "GPL-3.0",
    "gnu general public license version 2": "GPL-2.0",
    "apache license version 2 0": "Apache-2.0",
    "mozilla public license version 2 0": "MPL-2.0",
    "attribution noncommercial 4 0 international": "CC-BY-NC-4.0",
    "attribution sharealike 4 0 international": "CC-BY-SA-4.0",
    "attribution 4 0 international": "CC-BY-4.0",
    "cc0 1 0 universal": "CC0-1.0",
}

# Long licences speak of themselves all the way.
KEYWORD = re.compile(rb"licen[sc]e|copyright|spdx-|all rights reserved|creative commons|public domain|redistribution and use|hereby granted|\bcc by")
FILE_NAME = r"(?i)^(licen[sc]e|copying|notice|unlicense)([._-].*)?$"

#: Words of a long line that count as one.
LINE = 40
#: Neighbouring lines with such a cosine to any template are compared as one block.
NEAR = 0.2
LEAST = 0.5

#: A whole text is a licence with so high a cosine to one; a text from LONG words on may be a long licence:
#: it opens with a title, and most of it lies within REACH words of a keyword.
WHOLE = 0.8
LONG = 500
REACH = 60

#: Words in a smaller share of documents weigh no more than words in this share, so that scores don't move with the table's size.
FLOOR = 1e-3

# terms() of bytes: runs of ASCII letters and digits.
TERM_ENDS = BETWEEN.copy()
TERM_ENDS[128:] = True


def terms(text: str) -> list[str]:
    return re.findall(r"[a-z0-9]+", text.lower())


NAMES = [name for name, texts in TEMPLATES.items() for _ in texts]
KNOWN = [terms(t) for texts in TEMPLATES.values() for t in texts]
FULL_KNOWN = KNOWN + [terms(t) for t in FULL.values()]
FULL_NAMES = NAMES + list(FULL)
VOCABULARY = sorted({w for words in FULL_KNOWN for w in words})


def _hashes(words: list[str]) -> np.ndarray:
    """The kernel's hashes of single words."""
    return Words(*buffers(pa.array(words, pa.string())), TERM_ENDS).hashes(fold=True)


def document_frequency(docs: DataFrame) -> tuple[np.ndarray, int, dict[int, int]]:
    """Documents with each vocabulary word, documents, and those with each other word by its hash, over all of docs.

    Of the other words only those are returned that more than a FLOOR of the
    documents have: all others weigh the same, and there are at most 1 / FLOOR
    times the mean number of distinct words of a document.
    """
    known = np.sort(_hashes(VOCABULARY))

    def run(batches):
        for batch in blocks(batches):
            words = Words(*buffers(batch.column(0)), TERM_ENDS)
            own = words.hashes(fold=True)
            order = np.argsort(own, kind="stable")
            own, doc = own[order], words.doc[order]
            first = np.append(True, own[1:] != own[:-1])[: len(own)]
            # a word's documents come in order, so each is counted where it first comes
            new = first | np.append(True, doc[1:] != doc[:-1])[: len(own)]
            n_docs = np.add.reduceat(new.astype(np.int64), np.flatnonzero(first)) if len(own) else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(own[first].view(np.int64)), pa.array(n_docs)], ["term", "n"])

    counts = mapped(docs.select(F.col("text").cast("string").alias("text")), run, "term long, n long").groupBy("term").agg(F.sum("n").alias("n"))
    n = docs.count()
    sums = {r.term: r.n for r in counts.where(F.col("term").isin(known.view(np.int64).tolist()) | (F.col("n") > F.lit(FLOOR * n))).collect()}
    frequency = np.array([sums.pop(k, 0) for k in _hashes(VOCABULARY).view(np.int64).tolist()])
    return frequency, n, sums


def weight(frequency: np.ndarray, n: int) -> np.ndarray:
    """Inverse document frequency: a function of the share of documents alone, and never above that of the share FLOOR."""
    return 0.1 - np.log(np.clip(np.asarray(frequency) / max(n, 1), FLOOR, 1))


@dataclass
class TemplateIndex:
    """TF-IDF vectors of the templates over their own vocabulary, and the weights of other words that aren't rare."""

    idf: np.ndarray
    others: dict[int, float]

    @classmethod
    def of(cls, frequency: np.ndarray, n: int, others: dict[int, int] | None = None) -> TemplateIndex:
        others = others or {}
        return cls(weight(frequency, n), dict(zip(others, weight(np.array(list(others.values()), float), n).tolist(), strict=True)))

    def __post_init__(self):
        self.rare = float(weight(np.zeros(1), 1)[0])
        self.place = {w: k for k, w in enumerate(VOCABULARY)}
        self.rows = np.array([self.vector(words)[0] for words in FULL_KNOWN])
        self.rows /= np.linalg.norm(self.rows, axis=1, keepdims=True)
        hashes = _hashes(VOCABULARY)
        order = np.argsort(hashes)
        # sorted hashes of known and of other words, with their places or weights
        self.known_hash, self.known_place = hashes[order], order
        other = np.array(sorted(self.others), np.int64).view(np.uint64)
        order = np.argsort(other)
        self.other_hash, self.other_weight = other[order], np.array([self.others[k] for k in other[order].view(np.int64).tolist()])

    def cosines(self, hashes: np.ndarray, unit: np.ndarray, n_units: int) -> np.ndarray:
        """Cosine of each unit of words (ascending numbers, words by their hashes) to each template."""
        if not len(hashes):
            return np.zeros((n_units, len(self.rows)))
        order = np.lexsort((hashes, unit))
        value, own = hashes[order], unit[order]
        first = np.flatnonzero(np.append(True, (value[1:] != value[:-1]) | (own[1:] != own[:-1])))
        amount = np.log1p(np.diff(np.append(first, len(value))))
        value, own = value[first], own[first]
        at = np.minimum(np.searchsorted(self.known_hash, value), len(self.known_hash) - 1)
        hit = self.known_hash[at] == value
        place = self.known_place[at[hit]]
        load = np.full(len(value), self.rare)
        if len(self.other_hash):
            there = np.minimum(np.searchsorted(self.other_hash, value), len(self.other_hash) - 1)
            load = np.where(self.other_hash[there] == value, self.other_weight[there], load)
        load[hit] = self.idf[place]
        load *= amount
        norm = np.sqrt(np.bincount(own, load**2, n_units))
        owner, load = own[hit], load[hit]
        out = np.stack([np.bincount(owner, load * row[place], n_units) for row in self.rows], axis=1)
        return out / np.maximum(norm, 1e-12)[:, None]

    def vector(self, words: list[str]) -> tuple[np.ndarray, float]:
        """Weights of known words, and the squared weight of the others."""
        out, other = np.zeros(len(VOCABULARY)), {}
        for w in words:
            if (k := self.place.get(w)) is None:
                other[w] = other.get(w, 0) + 1
            else:
                out[k] += 1
        hashes = _hashes(list(other)).view(np.int64).tolist() if other else []
        return np.log1p(out) * self.idf, float(sum((np.log1p(c) * self.others.get(h, self.rare)) ** 2 for h, c in zip(hashes, other.values(), strict=True)))

    def best(self, words: list[str], names: list[str] = NAMES) -> tuple[str, float, int]:
        """Name and cosine of the nearest of the first templates, as many as names, and its place."""
        known, other = self.vector(words)
        norm = np.sqrt((known**2).sum() + other)
        if not norm:
            return names[0], 0.0, 0
        cosine = self.rows[: len(names)] @ known / norm
        k = int(cosine.argmax())
        return names[k], float(cosine[k]), k

    def long(self, text: bytes) -> tuple[str | None, float]:
        """The long licence that a text is, by its title and what it speaks of throughout, and the share of it near keywords."""
        opening = f" {' '.join(terms(text[: 16 * REACH].decode('utf-8', 'ignore'))[:REACH])} "
        at, name = min(((opening.find(f" {title} "), name) for title, name in TITLES.items() if f" {title} " in opening), default=(0, None))
        if name is None:
            return None, 0.0
        low, covered, end = text.lower(), 0, 0
        for m in KEYWORD.finditer(low):
            a, b = max(m.start() - 8 * REACH, end), min(m.end() + 8 * REACH, len(low))
            covered, end = covered + max(b - a, 0), max(end, b)
        return (name, covered / len(low)) if 2 * covered >= len(low) else (None, 0.0)

    def entire(self, text: bytes, k: int) -> bool:
        """Whether at least half of a text's words are those of a full text."""
        words = terms(text.decode("utf-8", "ignore"))
        return 2 * (Counter(words) & Counter(FULL_KNOWN[k])).total() >= len(words)


def lines(words: Words) -> np.ndarray:
    """Number of each word's line (LINE words of one at most), ascending through the block."""
    if not len(words.start):
        return np.zeros(0, np.int64)
    line = np.searchsorted(np.flatnonzero(words.data == 10), words.start)
    new = np.append(True, (line[1:] != line[:-1]) | (words.doc[1:] != words.doc[:-1]))
    first = np.flatnonzero(new)
    inside = np.arange(len(new)) - np.repeat(first, np.diff(np.append(first, len(new))))
    return np.cumsum(new | (inside % LINE == 0)) - 1


def notices(index: TemplateIndex, words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best template (an index of NAMES), its cosine and the words of the line or block of lines that has it, for each document."""
    n_docs = len(words.offsets) - 1
    name, score, size = np.zeros(n_docs, np.int64), np.zeros(n_docs), np.zeros(n_docs, np.int64)
    hashes, unit = words.hashes(fold=True), lines(words)

    def best(hashes, unit, doc_of):
        if not len(doc_of):
            return np.zeros(0)
        cosine = index.cosines(hashes, unit, len(doc_of))[:, : len(NAMES)]
        top, which = cosine.max(axis=1), cosine.argmax(axis=1)
        count = np.bincount(unit, minlength=len(doc_of))
        # of equal cosines the first counts
        for k in np.lexsort((-np.arange(len(top)), top)):
            if top[k] >= LEAST / 4 and top[k] >= score[doc_of[k]]:
                name[doc_of[k]], score[doc_of[k]], size[doc_of[k]] = which[k], top[k], count[k]
        return top

    if not len(unit):
        return name, score, size
    first = np.flatnonzero(np.append(True, unit[1:] != unit[:-1]))
    doc_of = words.doc[first]
    near = best(hashes, unit, doc_of) >= NEAR
    joined = near[1:] & near[:-1] & (doc_of[1:] == doc_of[:-1])
    if joined.any():
        block = np.cumsum(np.append(True, ~joined)) - 1
        inside = np.append(False, joined) | np.append(joined, False)
        number = np.full(len(near), -1)
        number[inside] = np.unique(block[inside], return_inverse=True)[1]
        own = number[unit]
        head = np.zeros(number.max() + 1, np.int64)
        head[number[inside]] = doc_of[inside]
        best(hashes[own >= 0], own[own >= 0], head)
    return name, score, size


def scanned(files: DataFrame, index: TemplateIndex, least: float = LEAST) -> DataFrame:
    """(doc_id, path, own, score, whole): the best notice of each file, and whether it is most of the file."""

    def run(batches):
        for batch in blocks(batches):
            own, tops, whole = [], [], []
            data, offsets = buffers(batch.column(2))
            words = Words(data, offsets, TERM_ENDS)
            found = notices(index, words)
            cosine = index.cosines(words.hashes(fold=True), words.doc, len(offsets) - 1)
            entire, high = cosine.argmax(axis=1), cosine.max(axis=1)
            for k, (which, top, size, n) in enumerate(zip(*(x.tolist() for x in (*found, words.count)), strict=True)):
                text = lambda k=k: data[offsets[k] : offsets[k + 1]].tobytes()
                name, full, share = NAMES[which], None, 0.0
                if n >= LONG:
                    full, share = index.long(text())
                if full is None and high[k] >= WHOLE and index.entire(text(), int(entire[k])):
                    full, share = FULL_NAMES[entire[k]], float(high[k])
                if full and share >= least:
                    name, top = full, max(top, share) if name == full else share
                own.append(name if top >= least else None)
                tops.append(top)
                whole.append(top >= least and (full is not None or 2 * size >= n))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(own, pa.string()), pa.array(tops, pa.float64()), pa.array(whole, pa.bool_())], ["doc_id", "path", "own", "score", "whole"])

    return mapped(files.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("path").cast("string").alias("path"), F.col("text").cast("string").alias("text")), run, "doc_id long, path string, own string, score double, whole boolean")


def _parent(path: Column) -> Column:
    """Directory of a path: what precedes the last slash, or the empty root."""
    return F.when(F.contains(path, F.lit("/")), F.regexp_replace(path, "/[^/]*$", "")).otherwise(F.lit(""))


def license_scan(files: DataFrame, scratch, least: float = LEAST) -> DataFrame:
    """(doc_id, path, license, score, how, source_dir) for each row of files (doc_id, path, text).

    how: `header` for a file's own notice, `inherited` for that of the nearest
    directory above with a licence file, null without either. Of several
    licence files in a directory the one with the highest (rounded) score counts, then
    the smaller path, then the licence's name. Null texts have no notice; null
    paths inherit nothing. A score is that of the best line or block; the score
    of a long licence is the share of its text near keywords.
    """
    index = TemplateIndex.of(*document_frequency(files))
    rows = scratch.keep(scanned(files, index, least).withColumn("dir", _parent(F.col("path"))))
    named = F.regexp_extract("path", r"([^/]*)$", 1).rlike(FILE_NAME)
    owners = rows.where(F.col("own").isNotNull() & F.col("path").isNotNull() & (F.col("whole") | named)).groupBy(F.col("dir").alias("source_dir")).agg(F.min_by("own", F.struct(-F.round("score", 6), F.col("path"), F.col("own"))).alias("inherited"))
    # directories, not files, look upwards: a directory is asked once however many files it holds
    dirs = rows.where(F.col("own").isNull() & F.col("path").isNotNull()).select("dir").distinct()
    parts = F.split("dir", "/")
    above = F.when(F.col("dir") == "", F.array(F.lit(""))).otherwise(F.concat(F.array(F.lit("")), F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.array_join(F.slice(parts, F.lit(1), k), "/"))))
    asked = dirs.select("dir", F.posexplode(above).alias("depth", "source_dir"))
    nearest = asked.join(owners, "source_dir").groupBy("dir").agg(F.max_by(F.struct("source_dir", "inherited"), "depth").alias("n"))
    joined = rows.join(nearest, "dir", "left")
    how = F.when(F.col("own").isNotNull(), "header").when(F.col("n").isNotNull() & F.col("path").isNotNull(), "inherited")
    return joined.select("doc_id", "path", F.when(how == "header", F.col("own")).when(how == "inherited", F.col("n.inherited")).alias("license"), F.round("score", 6).alias("score"), how.alias("how"), F.when(how == "inherited", F.col("n.source_dir")).alias("source_dir"))
