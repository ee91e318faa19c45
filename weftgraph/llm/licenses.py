"""License scan: winnowed template fingerprints pick candidates, banded alignment measures them.

Templates are few and given, so their inverted index (fingerprint to template
and position) travels with each task. A document's word shingles are looked
up in it; hits of one template close to one another in the document make a
candidate region, which a banded local alignment of words compares with the
template. Matches report how much of the template they cover and where they
lie in the text.

Shingle and window shrink for short templates, so that a text that changes or
leaves out as many words as the coverage allows, and adds none between them,
still has a run of words that holds a fingerprint.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.plans.common import ship

#: Fixed texts: license notices and short licenses, by SPDX name.
TEMPLATES = {
    "MIT-notice": "Released under the MIT License.",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
}

_WORD = re.compile(r"[A-Za-z0-9]+")
_TO_WORDS = bytes(c if chr(c).isascii() and chr(c).isalnum() else 32 for c in range(256))


@dataclass(frozen=True)
class LicenseParams:
    """Most words in a shingle, most shingles in a winnowing window, half width of the band, least coverage."""

    shingle: int = 3
    window: int = 2
    band: int = 16
    coverage: float = 0.8


def _words(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").lower().translate(_TO_WORDS).split()


def _hashes(ids: np.ndarray, k: int) -> np.ndarray:
    """Shingle hashes; 0 where a word is unknown."""
    n = len(ids) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    h, known = np.zeros(n, np.uint64), np.ones(n, bool)
    for j in range(k):
        part = ids[j : j + n]
        h = (h + part) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        known &= part > 0
    return np.where(known, h | np.uint64(1), np.uint64(0))


def winnow(h: np.ndarray, w: int) -> list[int]:
    """Places of the least hash of each window of w, the rightmost on ties."""
    out: list[int] = []
    for i in range(max(1, len(h) - w + 1)):
        part = h[i : i + w]
        if len(part):
            j = i + len(part) - 1 - int(part[::-1].argmin())
            if not out or out[-1] != j:
                out.append(j)
    return out


def lengths_for(words: int, params: LicenseParams) -> tuple[int, int]:
    """(shingle, window) of a template with so many words.

    ``lost`` words may be missing from a match, so the others hold a run of at
    least ``run`` words; a run of shingle + window - 1 words holds a fingerprint.
    """
    lost = words - math.ceil(words * params.coverage - 1e-9)
    run = -(-(words - lost) // (lost + 1))
    shingle = max(1, min(params.shingle, run))
    return shingle, max(1, min(params.window, run - shingle + 1))


class Index:
    """Vocabulary, templates as word ids, and the inverted index of their fingerprints."""

    def __init__(self, templates: dict[str, str], params: LicenseParams):
        self.params, self.names = params, sorted(templates)
        self.vocabulary: dict[bytes, int] = {}
        self.ids = []
        places: dict[int, dict[int, list[tuple[int, int]]]] = defaultdict(lambda: defaultdict(list))  # by shingle length
        for t, name in enumerate(self.names):
            words = _words(templates[name])
            ids = np.array([self.vocabulary.setdefault(w, xxhash.xxh3_64_intdigest(w) | 1) for w in words], np.uint64)
            self.ids.append(ids)
            shingle, window = lengths_for(len(ids), params)
            h = _hashes(ids, shingle)
            for p in winnow(h, window):
                places[shingle][int(h[p])].append((t, p))
        self.tables = [(k, np.array(sorted(table), np.uint64), table) for k, table in sorted(places.items())]

    def matches(self, text: str) -> list[tuple[str, int, int, float, int]]:
        """(template, start, end, coverage, matched words), best ones first where they overlap."""
        get = self.vocabulary.get
        words = _words(text)
        ids = np.fromiter((get(w, 0) for w in words), np.uint64, len(words))
        if not ids.any():
            return []
        by = defaultdict(list)
        for k, keys, table in self.tables:
            h = _hashes(ids, k)
            at = np.searchsorted(keys, h)
            for i in np.flatnonzero((h > 0) & (keys[np.minimum(at, len(keys) - 1)] == h)):
                for t, p in table[int(h[i])]:
                    by[t].append((int(i), p))
        found = []
        for t, hits in by.items():
            size, band = len(self.ids[t]), self.params.band
            region: list[tuple[int, int]] = []
            for i, p in [*hits, (None, None)]:
                if region and (i is None or i - region[-1][0] > size + band or region[-1][0] - region[0][0] > 2 * size + band):
                    lo = max(0, min(a - b for a, b in region) - band)
                    hi = min(len(ids), max(a - b for a, b in region) + size + band)
                    found += [(n, self.names[t], a, b, n / size) for n, a, b in self._copies(t, ids, lo, hi, region)]
                    region = []
                if i is not None:
                    region.append((i, p))
        found.sort(key=lambda x: (-x[0], x[2], x[1]))
        taken: list[tuple[int, int]] = []
        spans = None
        out = []
        for n, name, a, b, share in found:
            if any(a < y and x < b for x, y in taken):
                continue
            taken.append((a, b))
            spans = spans or [m.span() for m in _WORD.finditer(text)]
            out.append((name, spans[a][0], spans[b - 1][1], share, n))
        return out

    def _copies(self, t: int, ids: np.ndarray, lo: int, hi: int, region: list[tuple[int, int]]) -> Iterator[tuple[int, int, int]]:
        """(matched words, first, end) of each copy of a template in a region.

        The best alignment splits the region, and both sides are searched again
        as long as they have hits and words enough for another copy.
        """
        template, params = self.ids[t], self.params
        wanted = Counter(template.tolist())
        left = [(lo, hi, region)]
        while left:
            lo, hi, hits = left.pop()
            if not hits or (Counter(ids[lo:hi].tolist()) & wanted).total() / len(template) < params.coverage:
                continue
            got = align(template, ids[lo:hi], [i - p - lo for i, p in hits], params.band)
            if not got:
                continue
            n, a, b = got[0], lo + got[1], lo + got[2]
            if n / len(template) >= params.coverage:
                yield n, a, b
            left += [(lo, a, [h for h in hits if h[0] < a]), (b, hi, [h for h in hits if h[0] >= b])]


def align(template: np.ndarray, part: np.ndarray, diagonals: list[int], band: int) -> tuple[int, int, int] | None:
    """(matched words, first, end) of the best local alignment within a band.

    Cells lie on diagonals from the least hit's minus ``band`` to the largest
    hit's plus ``band``. A match scores 2, a mismatch or gap costs 1.
    """
    lo, hi = min(diagonals) - band, max(diagonals) + band
    width = hi - lo + 1
    score = np.zeros(width + 2, np.int64)
    count = np.zeros(width + 2, np.int64)
    start = np.zeros(width + 2, np.int64)
    best = (0, 0, 0, 0)
    for i in range(len(template)):
        new, cnt, beg = np.zeros_like(score), np.zeros_like(count), np.zeros_like(start)
        first, last = max(0, -(lo + i)), min(width, len(part) - (lo + i))
        for d in range(first, last):
            j = lo + i + d
            same = template[i] == part[j]
            options = [(int(score[d + 1]) + (2 if same else -1), int(count[d + 1]) + int(same), int(start[d + 1]) if score[d + 1] > 0 else j), (int(score[d + 2]) - 1, int(count[d + 2]), int(start[d + 2])), (int(new[d]) - 1, int(cnt[d]), int(beg[d]))]
            s, c, b = max(options, key=lambda o: (o[0], o[1]))
            if s > 0:
                new[d + 1], cnt[d + 1], beg[d + 1] = s, c, b
                if (s, c) > best[:2]:
                    best = (s, c, b, j + 1)
        score, count, start = new, cnt, beg
    return (best[1], best[2], best[3]) if best[0] > 0 else None


def _scan(templates: dict[str, str], params: LicenseParams):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Index(templates, params)
        for batch in batches:
            rows = [(i, *m) for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if t for m in index.matches(t)]
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["_id", "license", "start", "end", "coverage", "matched"])

    return run


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, params: LicenseParams = LicenseParams(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per match: id, license, start, end (code points), coverage, matched (words).

    Overlapping matches leave the one with the most matched words, then the
    first, then the smaller name. Null and empty texts match nothing; repeated
    rows report their matches each; null ids are allowed. An empty table or no
    templates give no rows. Extra columns are ignored.
    """
    ship(docs.sparkSession)
    base = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_text"))
    out = base.mapInArrow(_scan(TEMPLATES if templates is None else templates, params), "_id long, license string, start long, end long, coverage double, matched long")
    return out.withColumnRenamed("_id", id_col)
