"""License templates in texts: MinHash bands over overlapping windows retrieve, exact shingle containment verifies.

Templates are the full texts in license_texts and some short notices. Words are runs of ASCII letters and digits and other bytes, in lower
case; shingles have five words (a shorter template is one shingle). Templates of about equal length form a class with windows as long as
its longest one plus a stride, so every occurrence lies in a window whole. The least hashes of a window's shingles under several hash
functions are its MinHash; bands of ROWS of them are compared with the templates'. bands_for() gives the number of bands for which a window that
holds CONTAINMENT of a template's shingles is found with probability CONFIDENCE or more. Each window found is then compared with the
template shingle by shingle. A band can agree only where the window holds a shingle that is a template's least one, so windows without such an
anchor are passed over: the outcome is that of all windows, at the cost of one table look-up per word. Nothing is shuffled; templates
are a broadcast of known size.

Defined cases: null and empty text match nothing; of several occurrences of a template the best
is reported, of equal ones the first; repeated rows and extra columns do no harm; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from importlib.resources import files

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import by_size
from .plain import PLAIN as _PLAIN

SHINGLE, CONTAINMENT, ROWS, CONFIDENCE = 5, 0.8, 2, 0.999
#: Fixed texts: short public licence notices and opening paragraphs by identifier.
NOTICES = {
    "MIT-notice": "Released under the MIT License.",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "all-rights-reserved": "All rights reserved.",
    "MIT-opening": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions",
    "Apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "BSD-opening": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "GPL-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "ISC-opening": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
}


def license_texts() -> dict[str, str]:
    """Full texts and long notices, by identifier."""
    return {f.name.removesuffix(".txt"): f.read_text(encoding="utf-8") for f in sorted((files(__package__) / "license_texts").iterdir(), key=lambda f: f.name) if f.name.endswith(".txt")}


TEMPLATES = {**NOTICES, **license_texts()}
_ODD, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_LAST = np.uint64(0xFFFFFFFFFFFFFFFF)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ h >> np.uint64(31)) * _MIX
    return h ^ h >> np.uint64(29)


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(max(n, 1), base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """A hash per word of all texts, by a sum of bytes times powers that is brought back to the word's start; words per text."""
    plain = [(t or "").lower().encode("utf-8", "surrogatepass").translate(_PLAIN) for t in texts]
    data = np.frombuffer(b" ".join([b"", *plain, b""]), np.uint8)
    inside = (data != 32).astype(np.int8)
    edge = np.diff(inside, prepend=np.int8(0), append=np.int8(0))
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(_ODD, len(data)), dtype=np.uint64)])
    words = _mix((sums[ends] - sums[starts]) * _powers(_INVERSE, len(data))[starts] if len(starts) else np.zeros(0, np.uint64))
    bounds = np.cumsum([1, *(len(p) + 1 for p in plain)])
    return words, np.diff(np.searchsorted(starts, bounds))


def shingle_hashes(words: np.ndarray, per_text: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n words from each word on; all ones where the text ends before."""
    h = words.copy()
    for i in range(1, n):
        h = h * _ODD + np.concatenate([words[i:], np.zeros(min(i, len(words)), np.uint64)])
    h = _mix(h)
    left = np.repeat(np.cumsum(per_text), per_text) - np.arange(len(words))
    h[left < n] = _LAST
    return h


def bands_for(similarity: float, rows: int = ROWS, confidence: float = CONFIDENCE) -> int:
    """Bands with which sets of this Jaccard similarity share one with at least the confidence."""
    p = similarity**rows
    return 1 if p >= confidence else math.ceil(math.log(1 - confidence) / math.log(1 - p))


@dataclass
class Class:
    """Templates whose windows have one length: shingle width, window and stride in shingles, MinHash of each template."""

    width: int
    window: int
    stride: int
    names: list[str]
    sets: list[np.ndarray]
    seeds: np.ndarray
    rows: int
    keys: np.ndarray  # band, template


def _band_keys(minima: np.ndarray, rows: int) -> np.ndarray:
    """(functions, n) to (bands, n)."""
    parts = minima.reshape(-1, rows, minima.shape[1])
    out = parts[:, 0]
    for r in range(1, rows):
        out = _mix(out * _ODD + parts[:, r])
    return out


def classes(templates: dict[str, str] = TEMPLATES, containment: float = CONTAINMENT, rows: int = ROWS, confidence: float = CONFIDENCE) -> list[Class]:
    """Classes whose shortest template has at least four fifths of the shingles of the longest."""
    found: list[tuple[int, int, str, np.ndarray]] = []
    for name, text in templates.items():
        words, per = word_hashes([text])
        width = min(SHINGLE, len(words))
        if width:
            h = shingle_hashes(words, per, width)
            found.append((width, len(words) - width + 1, name, np.unique(h[h != _LAST])))
    found.sort(key=lambda x: x[:3])
    groups: list[list] = []
    for x in found:
        if groups and groups[-1][0][0] == x[0] and groups[-1][0][1] * 5 >= x[1] * 4:
            groups[-1].append(x)
        else:
            groups.append([x])
    out = []
    for g in groups:
        shortest, longest = g[0][1], g[-1][1]
        stride = max(1, shortest // 4)
        window = longest + stride - 1
        held = containment * min(len(x[3]) for x in g)
        bands = bands_for(min(1.0, held / (window + min(len(x[3]) for x in g) - held)), rows, confidence)
        seeds = np.random.default_rng(11).integers(1, 1 << 62, bands * rows, dtype=np.int64).astype(np.uint64) | np.uint64(1)
        keys = np.stack([_band_keys(np.array([[_mix(x[3] * s).min()] for s in seeds]), rows)[:, 0] for x in g], axis=1)
        out.append(Class(g[0][0], window, stride, [x[2] for x in g], [x[3] for x in g], seeds, rows, keys))
    return out


#: Bits of a shingle hash by which the table of anchors is looked up.
_TABLE = 20


def anchors(cs: list[Class]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Per shingle width a table of first bits, the sorted shingles that are least in a template under a function, and their classes as a matrix."""
    out = {}
    for width in {c.width for c in cs}:
        own = [(i, np.unique(np.concatenate([x[_mix(x[None] * c.seeds[:, None]).argmin(axis=1)] for x in c.sets]))) for i, c in enumerate(cs) if c.width == width]
        least = np.unique(np.concatenate([a for _, a in own]))
        belongs = np.zeros((len(least), len(cs)), bool)
        for i, a in own:
            belongs[np.searchsorted(least, a), i] = True
        table = np.zeros(1 << _TABLE, bool)
        table[(least >> np.uint64(64 - _TABLE)).astype(np.int64)] = True
        out[width] = (table, least, belongs)
    return out


def _anchored(h: np.ndarray, table: np.ndarray, least: np.ndarray, belongs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of anchors among the shingles, and which classes each belongs to."""
    at = np.flatnonzero(table[(h >> np.uint64(64 - _TABLE)).astype(np.int64)])
    rank = np.minimum(np.searchsorted(least, h[at]), len(least) - 1)
    hit = least[rank] == h[at]
    return at[hit], belongs[rank[hit]]


def matches(texts: list[str | None], cs: list[Class], containment: float = CONTAINMENT, marks: dict | None = None) -> list[tuple[int, str, float, int]]:
    """(text, template, best containment, word where it starts) for the texts of a slice; windows start anew in each text."""
    words, per_text = word_hashes(texts)
    if not len(words):
        return []
    ends = np.cumsum(per_text)
    best: dict[tuple[int, str], tuple[float, int]] = {}
    for width, found in (marks or anchors(cs)).items():
        h = shingle_hashes(words, per_text, width)
        spots, belongs = _anchored(h, *found)
        owner = np.searchsorted(ends, spots, side="right")
        for i in np.flatnonzero(belongs.any(axis=0)):
            c = cs[i]
            reach = -(-c.window // c.stride) * c.stride
            windows = set()
            for p, text in zip(spots[belongs[:, i]].tolist(), owner[belongs[:, i]].tolist()):
                at = p - int(ends[text] - per_text[text])
                windows.update((text, w) for w in range(max(0, (at - reach) // c.stride + 1), at // c.stride + 1))
            for text, w in sorted(windows):
                begin = int(ends[text] - per_text[text])
                lo = begin + w * c.stride
                part = h[lo : min(lo + reach, int(ends[text]))]
                part = part[part != _LAST]
                if not len(part):
                    continue
                minima = np.array([_mix(part * s).min() for s in c.seeds])
                keys = _band_keys(minima[:, None], c.rows)
                for t in np.flatnonzero((keys == c.keys).any(axis=0)).tolist():
                    own, name = c.sets[t], c.names[t]
                    inside = np.isin(part, own)
                    share = len(np.unique(part[inside])) / len(own)
                    if share >= containment:
                        new = (share, -(lo + int(np.flatnonzero(inside)[0]) - begin))
                        best[text, name] = max(new, best.get((text, name), new))
    return [(text, name, s, -first) for (text, name), (s, first) in sorted(best.items())]


def scan(docs: DataFrame, templates: dict[str, str] = TEMPLATES, containment: float = CONTAINMENT, rows: int = ROWS, confidence: float = CONFIDENCE) -> DataFrame:
    """doc_id, license_id, containment, first_word: a row per document and template found in it."""
    cs = classes(templates, containment, rows, confidence)
    sent = docs.sparkSession.sparkContext.broadcast((cs, anchors(cs)))
    kind = docs.schema["doc_id"].dataType.simpleString()

    def find(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for p in by_size(b):
                got = matches(p.column("text").to_pylist(), sent.value[0], containment, sent.value[1])
                ids = p.column("doc_id").take(pa.array([g[0] for g in got], pa.int64()))
                rest = [pa.array([g[i] for g in got], t) for i, t in ((1, pa.string()), (2, pa.float64()), (3, pa.int64()))]
                yield pa.RecordBatch.from_arrays([ids, *rest], names=["doc_id", "license_id", "containment", "first_word"])

    rows_in = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return rows_in.mapInArrow(find, f"doc_id {kind}, license_id string, containment double, first_word bigint")


def op9_licenses(spark, sf_dir: str) -> DataFrame:
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
