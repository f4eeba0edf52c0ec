"""Licence scan: MinHash bands over overlapping windows retrieve templates, exact containment verifies.

Words are compared without case and signs, as shingles of five words. For each template length windows
of that many words overlap in all but one; a window with at least ``CONTAINED`` of a template's shingles
has a Jaccard similarity of J = c / (2 - c) or more with it, and ``BANDS`` bands of ``ROWS`` rows miss it
with a probability of (1 - J**ROWS)**BANDS, under one in a hundred thousand. Windows without a single shingle of any
template cannot match and get no signature.

One row per match: overlapping windows of one template give the best one. Null, empty and short texts
match nothing; repeated rows are scanned each; other columns are not read.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import FOLD, HashSet, _mix, gram_hashes, table, text_slices, word_hashes

#: Fixed public notices.
TEMPLATES = {
    "MIT": "Released under the MIT License.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "MIT-notice": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction",
    "Apache-2.0-notice": "you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "GPL-3.0-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "BSD-notice": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "MPL-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "Unlicense-notice": "This is free and unencumbered software released into the public domain.",
    "ISC-notice": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
    "CC-BY-4.0-notice": "This work is licensed under a Creative Commons Attribution 4.0 International License",
}
SHINGLE, CONTAINED, BANDS, ROWS = 5, 0.8, 20, 2
_MATCHES = "doc_id long, license string, start_word int, end_word int, shared int, of int"


class TemplateIndex:
    """Templates by band keys; as large as the templates."""

    def __init__(self, templates: dict[str, str]):
        self.sets: dict[str, np.ndarray] = {}
        self.by_length: dict[int, dict[tuple[int, int], list[str]]] = defaultdict(lambda: defaultdict(list))
        for name, text in templates.items():
            h, _, _, _ = word_hashes([text.encode().translate(FOLD)])
            grams = gram_hashes(h, min(SHINGLE, len(h)))
            if len(h) < SHINGLE:
                raise ValueError(f"template {name} has fewer than {SHINGLE} words")
            self.sets[name] = np.unique(grams)
            for key in self.keys(grams[None, :]):
                self.by_length[len(h)][key[0]].append(name)
        self.by_length = {m: dict(v) for m, v in self.by_length.items()}
        self.any = HashSet(np.concatenate(list(self.sets.values())))

    @staticmethod
    def keys(windows: np.ndarray) -> list[list[tuple[int, int]]]:
        """Per band, the (band, key) of each window; windows: (n, shingles)."""
        out = []
        for band in range(BANDS):
            key = np.zeros(len(windows), np.uint64)
            for row in range(ROWS):
                seed = np.uint64((band * ROWS + row + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
                key = _mix(key + _mix(windows ^ seed).min(axis=1))
            out.append([(band, int(k)) for k in key])
        return out

    def scan(self, grams: np.ndarray, hits: np.ndarray) -> list[tuple[str, int, int, int, int]]:
        """(template, first word, word after, shared shingles, of) in one text; hits: its places of template shingles."""
        best: dict[str, list[tuple[str, int, int, int, int]]] = defaultdict(list)
        for m, index in self.by_length.items():
            width = m - SHINGLE + 1
            first = np.unique((hits[:, None] - np.arange(width)).ravel())
            first = first[(first >= 0) & (first + width <= len(grams))]
            if not len(first):
                continue
            windows = grams[first[:, None] + np.arange(width)]
            asked: dict[int, set[str]] = defaultdict(set)
            for band in self.keys(windows):
                for i, key in enumerate(band):
                    if names := index.get(key):
                        asked[i].update(names)
            for i, names in sorted(asked.items()):
                for name in names:
                    own = self.sets[name]
                    shared = len(np.intersect1d(windows[i], own))
                    if shared >= CONTAINED * len(own):
                        at = int(first[i])
                        if best[name] and at < best[name][-1][2]:
                            if shared > best[name][-1][3]:
                                best[name][-1] = (name, at, at + m, shared, len(own))
                        else:
                            best[name].append((name, at, at + m, shared, len(own)))
        return [x for found in best.values() for x in found]


def license_matches(docs: DataFrame, templates: dict[str, str] = TEMPLATES) -> DataFrame:
    index = TemplateIndex(templates)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").to_pylist()
            for a, _, texts in text_slices(batch):
                h, offsets, _, _ = word_hashes([t.translate(FOLD) for t in texts])
                grams = gram_hashes(h, SHINGLE)
                hits = index.any.where(grams)
                owner = np.searchsorted(offsets, hits, "right") - 1
                inside = hits + SHINGLE <= offsets[owner + 1]
                hits, owner = hits[inside], owner[inside]
                rows = []
                for i in np.unique(owner):
                    s = offsets[i]
                    own = grams[s : offsets[i + 1] - SHINGLE + 1]
                    rows += [(ids[a + i], *x) for x in index.scan(own, hits[owner == i] - s)]
                if rows:
                    kinds = (pa.int64(), pa.string(), *[pa.int32()] * 4)
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[x.split()[0] for x in _MATCHES.split(", ")])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(scan, _MATCHES)


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_matches(table(spark, sf_dir, "documents"))
