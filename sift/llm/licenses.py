"""License scans: winnowed fingerprints pick candidate templates, banded alignment tells coverage and spans.

Templates are normalised to words; the hashes of their runs of a few words are winnowed, and the kept ones form an
inverted index from hash to template and position. A document looks up all its runs, so that any shared passage of
``guarantee`` words meets the index. Edits may leave no such passage, so of each template single words are indexed too:
one more than may be missing from a place that is reported, the longest ones, so that any such place holds one of them.
Hits whose diagonals agree make a candidate region. Where it holds enough of the template's words in any order, it is
aligned word by word with the template inside a band around the diagonal; matched words give coverage and span. Found is
thus every place whose matched words lie on diagonals no farther apart than the band.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sift.llm.decontam import _IS_WORD, words_of
from sift.llm.textbatch import ASCII_LOWER, flat, slices, word_bounds, word_keys
from sift.runtime import ship_package

#: Words of a run, and words of a shared passage that is sure to meet the index.
RUN = 3
GUARANTEE = 5
#: Words by which an alignment may leave its diagonal.
BAND = 8
#: Matched words of a template by which it is reported, in a hundred.
MIN_COVERAGE = 80

#: Names and texts of public license notices.
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("MIT", "Released under the MIT License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("MIT-grant", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
)

_MIX = np.uint64(0x9E3779B97F4A7C15)


def run_hashes(keys: np.ndarray, run: int) -> np.ndarray:
    """Hash of the run of words that begins at each word but the last ones."""
    n = max(0, len(keys) - run + 1)
    h = np.zeros(n, np.uint64)
    for k in range(run):
        h = (h ^ keys[k : k + n]) * _MIX
        h ^= h >> np.uint64(29)
    return h


def winnow(hashes: np.ndarray, window: int) -> list[int]:
    """Positions of the least hash of every window, the rightmost on a tie; of a shorter sequence its least."""
    if not len(hashes):
        return []
    kept = []
    for a in range(max(1, len(hashes) - window + 1)):
        part = hashes[a : a + window]
        at = a + len(part) - 1 - int(np.argmin(part[::-1]))
        if not kept or kept[-1] != at:
            kept.append(at)
    return kept


class Index:
    """Templates as words, and the inverted indexes of their winnowed runs and of the words of which one is sure to be met."""

    def __init__(self, templates, run: int = RUN, guarantee: int = GUARANTEE, min_coverage: int = MIN_COVERAGE):
        self.names, self.words, self.bags = [], [], []
        self.at: dict[int, dict[int, list[tuple[int, int]]]] = {run: defaultdict(list), 1: defaultdict(list)}
        for name, text in templates:
            words = words_of(text)
            if not words:
                continue
            size = np.array(list(map(len, words)), np.int64)
            end = np.cumsum(size)
            keys = word_keys(np.frombuffer(b"".join(words), np.uint8), end - size, end)
            hashes = run_hashes(keys, run)
            for p in winnow(hashes, guarantee - run + 1):
                self.at[run][int(hashes[p])].append((len(self.names), p))
            may_miss = len(words) * (100 - min_coverage) // 100
            single = run_hashes(keys, 1)
            for p in sorted(range(len(words)), key=lambda p: -size[p])[: may_miss + 1]:
                self.at[1][int(single[p])].append((len(self.names), p))
            self.names.append(name)
            self.words.append(words)
            self.bags.append(Counter(words))
        self.hashes = {r: np.array(sorted(at), np.uint64) for r, at in self.at.items()}

    def hits(self, keys: np.ndarray) -> Iterator[tuple[int, int, list[tuple[int, int]]]]:
        """(word at which an indexed run begins, its length, the templates and positions)."""
        for run, known in self.hashes.items():
            h = run_hashes(keys, run)
            if len(h) and len(known):
                where = np.minimum(np.searchsorted(known, h), len(known) - 1)
                for w in np.flatnonzero(known[where] == h).tolist():
                    yield w, run, self.at[run][int(h[w])]


def align(template: list[bytes], text: list[bytes], shift: int, band: int) -> tuple[int, int, int]:
    """Longest common subsequence within a band: matched words, and the first and last+1 text word matched.

    ``text`` word j belongs near template word j - shift; cells farther than ``band`` from that diagonal are not filled.
    """
    n, m = len(template), len(text)
    below: dict[int, tuple[int, int, int]] = {}
    for i in range(1, n + 1):
        row: dict[int, tuple[int, int, int]] = {}
        left = (0, -1, -1)
        for j in range(max(1, i + shift - band), min(m, i + shift + band) + 1):
            best = max(left, below.get(j, (0, -1, -1)), key=lambda x: x[0])
            if template[i - 1] == text[j - 1]:
                score, first, _ = below.get(j - 1, (0, -1, -1))
                if score + 1 > best[0]:
                    best = (score + 1, first if score else j - 1, j)
            row[j] = left = best
        below = row
    return max(below.values(), key=lambda x: x[0], default=(0, -1, -1))


def scan_words(words: list[bytes], hits: list[tuple[int, int, int]], index: Index, band: int, min_coverage: int) -> list[tuple[str, int, int, int, int]]:
    """(name, matched, template words, first word, last word + 1) of each template region; hits are (word, template, position).

    Of overlapping regions of a template the best matched is kept, and the others are aligned again beside it.
    """
    regions: dict[tuple[int, int], set[int]] = defaultdict(set)
    for w, t, p in hits:
        regions[t, w - p].add(w)

    def aligned(t: int, diagonal: int, a: int, b: int) -> tuple[int, int, int] | None:
        n = len(index.words[t])
        a, b = max(a, diagonal - band), min(b, diagonal + n + band)
        held = Counter(words[a:b])
        if 100 * sum(min(c, held[w]) for w, c in index.bags[t].items()) < min_coverage * n:
            return None
        matched, first, last = align(index.words[t], words[a:b], diagonal - a, band)
        return (matched, a + first, a + last) if matched and 100 * matched >= min_coverage * n else None

    found = [(t, diagonal, got) for t, diagonal in sorted(regions) if (got := aligned(t, diagonal, 0, len(words)))]
    out, taken = [], defaultdict(list)
    for t, diagonal, (matched, first, last) in sorted(found, key=lambda x: (x[0], -x[2][0], x[2][2] - x[2][1], x[1])):
        if any(first < y and x < last for x, y in taken[t]):
            free = [w for w in regions[t, diagonal] if not any(x <= w < y for x, y in taken[t])]
            if not free:
                continue
            got = aligned(t, diagonal, max((y for _, y in taken[t] if y <= free[0]), default=0), min((x for x, _ in taken[t] if x > free[0]), default=len(words)))
            if not got:
                continue
            matched, first, last = got
        out.append((index.names[t], matched, len(index.words[t]), first, last))
        taken[t].append((first, last))
    return out


_FOUND = pa.list_(pa.struct([("license", pa.string()), ("matched", pa.int32()), ("words", pa.int32()), ("start", pa.int32()), ("end", pa.int32())]))


def _scan(index: Index, band: int, min_coverage: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                buf, offsets = flat(part.column("text"))
                buf = ASCII_LOWER[buf]
                starts, ends, first = word_bounds(buf, offsets, _IS_WORD)
                raw = buf.tobytes()
                by_doc: dict[int, list] = defaultdict(list)
                met = list(index.hits(word_keys(buf, starts, ends)))
                owner = np.searchsorted(first, np.array([w for w, _, _ in met], np.int64), side="right") - 1
                for (w, run_words, places), d in zip(met, owner.tolist(), strict=True):
                    if w + run_words <= first[d + 1]:
                        by_doc[d] += [(w - int(first[d]), t, p) for t, p in places]
                docs, rows = [], []
                for d, hits in by_doc.items():
                    a, b = int(first[d]), int(first[d + 1])
                    words = [raw[x:y] for x, y in zip(starts[a:b].tolist(), ends[a:b].tolist(), strict=True)]
                    for name, matched, n, s, e in scan_words(words, hits, index, band, min_coverage):
                        docs.append(d)
                        rows.append((name, matched, n, int(starts[a + s] - offsets[d]), int(ends[a + e - 1] - offsets[d])))
                cols = list(zip(*rows, strict=True)) or [()] * 5
                yield pa.RecordBatch.from_arrays([part.column("doc").take(pa.array(docs, pa.int64())), *(pa.array(c, k) for c, k in zip(cols, (pa.string(), *[pa.int32()] * 4), strict=True))], ["doc", "license", "matched", "words", "start", "end"])

    return run


def license_spans(docs: DataFrame, templates=TEMPLATES, id_col: str = "doc_id", text_col: str = "text", band: int = BAND, min_coverage: int = MIN_COVERAGE) -> DataFrame:
    """(doc, license, matched, words, start, end): each place where a template's words are matched well enough.

    start and end are byte offsets in the text; matched of words tells the coverage. The templates are few and given by
    the caller. Null and empty texts have none; repeated rows report each; other columns are not looked at.
    """
    ship_package(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_scan(Index(templates, min_coverage=min_coverage), band, min_coverage), "doc long, license string, matched int, words int, start int, end int")


def op4_license_scans(spark, sf_dir: str) -> DataFrame:
    """License notices in all documents, with coverage in a hundred."""
    found = license_spans(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(F.col("doc").alias("doc_id"), "license", "matched", "words", F.round(100 * F.col("matched") / F.col("words"), 2).alias("coverage"), "start", "end")
