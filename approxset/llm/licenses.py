"""License scan: winnowed template fingerprints in an inverted index pick candidates, banded alignment confirms them.

Texts and templates are sequences of lower-cased alphanumeric words. Of each template the winnowed k-gram hashes (the
least of every `window` neighbours, the rightmost of equals) are indexed with their places. A document's k-grams are
looked up in the index; hits of a template whose diagonals lie no further apart than the template is long make a
candidate region, which a local alignment scores, within a band around those diagonals; the band widens while that finds
more, and to the template's length before a region is given up. Hits outside of the reported region start regions of
their own. A match reports the share of the template's words that align, and the
span of the document in bytes and text. Templates are a bounded parameter and go to every task; documents never move.

Defined results: a null or empty text matches nothing; each region of a document gives its own row, so repeated license
lines are all reported; documents without a match give no row; repeated rows give repeated results; an empty table
gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit
from .common import documents, ship

#: Well-known public license notices.
TEMPLATES = {
    "MIT-line": "Released under the MIT License.",
    "Apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-line": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-line": "Licensed under CC BY-NC 4.0.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "Apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "GPL-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
}
_NOT_WORD = np.ones(256, bool)
_NOT_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False
SCHEMA = "doc_id long, license string, coverage double, matched_words int, template_words int, start_byte long, end_byte long, span string"


def _words(texts: list[bytes]):
    return textkit.words(texts, separators=_NOT_WORD)


def grams(h: np.ndarray, k: int) -> np.ndarray:
    n = max(0, len(h) - k + 1)
    acc = np.zeros(n, np.uint64)
    for i in range(k):
        acc = acc * np.uint64(0xD6E8FEB86659FD93) + h[i : i + n]
    return textkit.mix(acc)


def winnow(g: np.ndarray, window: int) -> np.ndarray:
    """Places of the fingerprints: in each window the least hash, the rightmost of equals."""
    if len(g) <= window:
        return np.array([len(g) - 1 - int(g[::-1].argmin())]) if len(g) else np.zeros(0, int)
    v = np.lib.stride_tricks.sliding_window_view(g, window)
    return np.unique(np.arange(len(v)) + window - 1 - v[:, ::-1].argmin(1))


class Index:
    """Inverted index: fingerprint -> (template, place)."""

    def __init__(self, templates: dict[str, str], k: int, window: int):
        self.names, self.k = sorted(templates), k
        self.words = [_words([templates[n].encode()])[3] for n in self.names]
        posts = []
        for t, h in enumerate(self.words):
            g = grams(h, min(k, len(h))) if len(h) >= k else np.zeros(0, np.uint64)
            posts += [(int(g[p]), t, int(p)) for p in winnow(g, window)]
        posts.sort()
        self.keys = np.array([p[0] for p in posts], np.uint64)
        self.template = np.array([p[1] for p in posts], int)
        self.place = np.array([p[2] for p in posts], int)

    def hits(self, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place among g, posting) pairs."""
        lo, hi = np.searchsorted(self.keys, g, "left"), np.searchsorted(self.keys, g, "right")
        n = hi - lo
        at = np.repeat(np.arange(len(g)), n)
        return at, np.arange(len(at)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)


def align(doc: np.ndarray, template: np.ndarray, diagonal: int, band: int, spread: int = 0) -> tuple[int, int, int]:
    """Local alignment from `band` below the diagonal (document place minus template place) to `band` above diagonal +
    `spread`: words matched, and the first and last document word. A match scores 2, a gap or mismatch -1."""
    m, width = len(template), 2 * band + spread + 1
    back = np.zeros((m + 1, width), np.int8)
    above, column = np.zeros(width + 1, int), np.arange(width)
    low = diagonal - band
    best, at = 0, None
    for i in range(1, m + 1):
        j = column + (i - 1 + low)
        inside = (j >= 0) & (j < len(doc))
        slant = above[:-1] - 1
        slant[inside] += 3 * (doc[j[inside]] == template[i - 1])
        up = above[1:] - 1
        score = np.where(inside, np.maximum(np.maximum(slant, up), 0), 0)
        score = np.where(inside, np.maximum.accumulate(score + column) - column, 0)  # gaps along the row
        back[i] = np.where(score == 0, 0, np.where(score == slant, 1, np.where(score == up, 2, 3)))
        c = int(score.argmax())
        if score[c] > best:
            best, at = int(score[c]), (i, c)
        above[:-1] = score
    if at is None:
        return 0, 0, 0
    i, c = at
    last = first = i - 1 + c + low
    matched = 0
    while i > 0 and back[i, c]:
        j = i - 1 + c + low
        if back[i, c] == 1:
            matched += int(template[i - 1] == doc[j])
            first = j
            i -= 1
        elif back[i, c] == 2:
            i, c = i - 1, c + 1
        else:
            c -= 1
    return matched, first, last


def regions(doc: np.ndarray, template: np.ndarray, at: np.ndarray, diagonal: np.ndarray, band: int, least: float):
    """(words matched, first, last document word) of each region of a document that holds the template; `at` are the
    document places of the hits. Words of a reported region are not used again; a hit outside of all regions starts one."""
    doc, spare = doc.copy(), np.uint64((int(template.max()) + 1) % (1 << 64))
    reach = max(band, len(template))
    order = np.lexsort((at, diagonal))
    at, diagonal = at[order], diagonal[order]
    while len(at):
        d = int(diagonal[0])
        spread = int(diagonal[np.searchsorted(diagonal, d + reach, "right") - 1]) - d
        # the band widens while that finds more words, and to the template's length before a region is given up
        wide, matched = band, -1
        while True:
            base, before = max(0, d - wide), matched
            matched, first, last = align(doc[base : d + spread + len(template) + wide + 1], template, d - base, wide, spread)
            if wide >= reach or matched == len(template) or (matched <= before and matched / len(template) >= least):
                break
            wide = min(2 * wide, reach) if matched / len(template) >= least or before < 0 else reach
        if matched / len(template) >= least:
            yield matched, first + base, last + base
            doc[first + base : last + base + 1] = spare
            left = (at < first + base) | (at > last + base)
            left &= (diagonal != d) | (at != at[0])
        else:
            left = diagonal != d
        at, diagonal = at[left], diagonal[left]


def _scanner(templates: dict[str, str], k: int, window: int, band: int, least: float):
    def run(batches):
        index = Index(templates, k, window)
        for batch in batches:
            ids = batch.column(0).to_pylist()
            out = []
            for lo, hi, texts in textkit.groups_of_rows(batch, "text"):
                row, start, size, h = _words(texts)
                at, post = index.hits(grams(h, k))
                fine = row[at] == row[np.minimum(at + k - 1, len(row) - 1)] if len(at) else np.zeros(0, bool)
                at, post = at[fine], post[fine]
                if not len(at):
                    continue
                bounds = textkit.bounds(row, hi - lo)
                r, t = row[at], index.template[post]
                diagonal = at - bounds[r] - index.place[post]
                order = np.lexsort((t, r))
                r, t, diagonal, place = r[order], t[order], diagonal[order], (at - bounds[r])[order]
                new = np.flatnonzero(np.append(True, (np.diff(r) != 0) | (np.diff(t) != 0)))
                for b, e in zip(new, np.append(new[1:], len(r)), strict=True):
                    i, w = int(r[b]), index.words[t[b]]
                    x, y = bounds[i], bounds[i + 1]
                    for matched, first, last in regions(h[x:y], w, place[b:e], diagonal[b:e], band, least):
                        s, e_ = int(start[first + x]), int(start[last + x] + size[last + x])
                        out.append((ids[lo + i], index.names[t[b]], round(matched / len(w), 6), matched, len(w), s, e_, texts[i][s:e_].decode("utf-8", "replace")))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out, strict=True), (pa.int64(), pa.string(), pa.float64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.string()), strict=True)], names=["doc_id", "license", "coverage", "matched_words", "template_words", "start_byte", "end_byte", "span"])

    return run


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, k: int = 3, window: int = 3, band: int = 6, least: float = 0.7, key: str = "doc_id") -> DataFrame:
    """One row per matched region, see the module. A template needs at least k words to be found."""
    ship(docs.sparkSession)
    return docs.select(F.col(key).cast("long").alias("doc_id"), "text").mapInArrow(_scanner(templates or TEMPLATES, k, window, band, least), SCHEMA)


def op1_license_scan(spark, sf_dir: str) -> DataFrame:
    return scan_licenses(documents(spark, sf_dir))
