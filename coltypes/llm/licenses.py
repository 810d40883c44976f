"""License scans: an inverted index of winnowed template fingerprints picks candidates, banded alignment confirms them.

Templates and texts are reduced to ASCII letters and digits in lower case (bytes of other scripts
stay). Of the runs of ``gram`` characters of a template, winnowing keeps the least hash of each
window of ``window``, so any shared stretch of ``gram + window - 1`` characters holds an indexed run.
All runs of every whole document are looked up. Hits of a template on neighbouring diagonals make a
candidate place, where the words of template and document are aligned within a band (match 2,
mismatch and gap -1). The share of the template's words that are matched is the coverage; of
overlapping places the one with most matched words, then the higher coverage, is kept.

Defined cases: null text counts as empty; a template without words is ignored; equal templates
report the alphabetically first name; repeated rows are reported each.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.llm import common, wordhash

# Short notices by which texts declare public licenses.
NOTICES = {
    "mit": "Released under the MIT License.",
    "mit-permission": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software",
    "apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "gpl-2": "This work is licensed under the GNU General Public License, version 2.",
    "gpl-3": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "lgpl-notice": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation",
    "bsd-redistribution": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "isc-permission": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "cc-by-4.0": "Licensed under CC BY 4.0.",
    "cc-by-sa-4.0": "Licensed under CC BY-SA 4.0.",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0.",
    "cc-by-nc-nd-4.0": "Licensed under CC BY-NC-ND 4.0.",
    "cc0-1.0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "unlicense": "This is free and unencumbered software released into the public domain.",
}

_CODE = np.zeros(256, np.uint64)
for _c in range(128):
    if chr(_c).isalnum():
        _CODE[_c] = int(chr(_c), 36) + 1
_CODE[128:] = 37 + (np.arange(128, dtype=np.uint64) % 27)


@dataclass(frozen=True)
class Settings:
    gram: int = 10
    window: int = 6
    band: int = 6
    coverage: float = 0.8


def _runs(raw: np.ndarray, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Mixed codes of all runs of ``gram`` kept bytes (up to 10), and the places of all kept bytes."""
    at = np.flatnonzero(wordhash.ALNUM_WORDS[raw])
    n = len(at) - gram + 1
    if n <= 0:
        return np.zeros(0, np.uint64), at
    one = _CODE[raw[at]]
    out, done = np.zeros(n, np.uint64), 0
    while done < gram:  # runs of 1, 2, 4, ... characters, six bits each
        size, part = 1, one
        while size * 2 <= gram - done:
            part = part[: len(part) - size] | (part[size:] << np.uint64(6 * size))
            size *= 2
        out |= part[done : done + n] << np.uint64(6 * done)
        done += size
    return wordhash.mix(out), at


def winnowed(hashes: np.ndarray, window: int) -> np.ndarray:
    """Places of the least hash (the rightmost of equals) of each window."""
    if not len(hashes):
        return np.zeros(0, np.int64)
    size = min(window, len(hashes))
    windows = np.lib.stride_tricks.sliding_window_view(hashes, size)[:, ::-1]
    return np.unique(np.arange(len(windows)) + size - 1 - windows.argmin(axis=1))


def align(template: list[int], text: list[int], diagonal: int, band: int) -> tuple[int, int, int]:
    """Best local alignment near a diagonal (text place minus template place): matched words, first and last + 1 word of the text."""
    best, above = (0, 0, 0, 0), {}
    for i, word in enumerate(template):
        row = {}
        for j in range(max(0, i + diagonal - band), min(len(text), i + diagonal + band + 1)):
            # (score, matched, first, last)
            came = above.get(j - 1, (0, 0, j, j))
            same = word == text[j]
            options = [(came[0] + (2 if same else -1), came[1] + same, came[2], j + 1)]
            if j in above:
                options.append((above[j][0] - 1, *above[j][1:]))
            if j - 1 in row:
                options.append((row[j - 1][0] - 1, *row[j - 1][1:]))
            got = max(options, key=lambda o: (o[0], o[1], -o[3]))
            if got[0] > 0:
                row[j] = got
                if (got[0], got[1]) > best[:2]:
                    best = got
        above = row
    return best[1], best[2], best[3]


class Index:
    """Templates and the sorted fingerprints that point into them; its size follows the templates given."""

    def __init__(self, templates: dict[str, str], s: Settings):
        self.s, self.names, self.words, seeds, owners = s, [], [], [], []
        seen = set()
        for name in sorted(templates):
            raw, offsets = wordhash.utf8(pa.array([templates[name]], pa.string()))
            hashes, starts, _, _ = wordhash.words(raw, offsets, wordhash.ALNUM_WORDS)
            if not len(hashes) or hashes.tobytes() in seen:
                continue
            seen.add(hashes.tobytes())
            runs, at = _runs(raw, s.gram)
            kept = winnowed(runs, s.window)
            seeds.append(runs[kept])
            owners += [(len(self.names), w) for w in (np.searchsorted(starts, at[kept], "right") - 1).tolist()]
            self.names.append(name), self.words.append(hashes.tolist())
        seeds = np.concatenate(seeds) if seeds else np.zeros(0, np.uint64)
        order = np.argsort(seeds, kind="stable")
        self.seeds, self.owners = seeds[order], [owners[k] for k in order]
        self.marks = np.zeros(1 << 16, bool)
        self.marks[self.seeds & np.uint64(0xFFFF)] = True

    def find(self, column: pa.Array) -> list[tuple[int, str, float, int, int, int]]:
        """(row, template, coverage, matched words, first and end code point) of whole texts."""
        raw, offsets = wordhash.utf8(column)
        runs, at = _runs(raw, self.s.gram)
        near = np.flatnonzero(self.marks[runs & np.uint64(0xFFFF)])
        low, high = (np.searchsorted(self.seeds, runs[near], side) for side in ("left", "right"))
        near, low, high = (x[low < high] for x in (near, low, high))
        places = at[near]
        rows = np.searchsorted(offsets, places, "right") - 1
        whole = at[near + self.s.gram - 1] < offsets[rows + 1] if len(near) else np.zeros(0, bool)
        hits: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
        for row, place, x, y in zip(rows[whole].tolist(), places[whole].tolist(), low[whole].tolist(), high[whole].tolist(), strict=True):
            hits[row] += [(*self.owners[k], place) for k in range(x, y)]
        out = []
        for row, found in hits.items():
            own = raw[offsets[row] : offsets[row + 1]]
            hashes, starts, ends, _ = wordhash.words(own, np.array([0, len(own)]), wordhash.ALNUM_WORDS)
            out += [(row, *f) for f in self._confirmed(found, own, hashes, starts, ends, int(offsets[row]))]
        return out

    def _confirmed(self, found: list, own: np.ndarray, hashes: np.ndarray, starts: np.ndarray, ends: np.ndarray, begin: int) -> list[tuple]:
        spots = defaultdict(set)
        for template, word, place in found:
            spots[template].add(int(np.searchsorted(starts, place - begin, "right")) - 1 - word)
        places = []
        for template, diagonals in spots.items():
            words, last = self.words[template], None
            for d in sorted(diagonals):
                if last is not None and d - last <= self.s.band // 2:
                    continue
                last = d
                low = max(0, d - self.s.band)
                text = hashes[low : d + len(words) + self.s.band + 1].tolist()
                matched, first, end = align(words, text, d - low, self.s.band)
                if matched >= self.s.coverage * len(words):
                    places.append((matched, matched / len(words), self.names[template], low + first, low + end))
        out, taken = [], []
        for matched, coverage, name, first, end in sorted(places, key=lambda p: (-p[0], -p[1], p[2], p[3])):
            if all(end <= x or y <= first for x, y in taken):
                taken.append((first, end))
                char = [int(((own[:b] & 0xC0) != 0x80).sum()) for b in (starts[first], ends[end - 1])]
                out.append((name, coverage, matched, *char))
        return sorted(out, key=lambda o: o[3])


FOUND = "doc_id long, license string, coverage double, matched_words int, start long, end long"


def scan(docs: DataFrame, templates: dict[str, str] | None = None, settings: Settings = Settings()) -> DataFrame:
    """One row per license notice in a document: its coverage and its span in code points, end exclusive."""
    spark = common.prepare(docs.sparkSession)
    held = spark.sparkContext.broadcast(Index(NOTICES if templates is None else templates, settings))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in common.pieces(whole, "text"):
                got = held.value.find(batch.column("text"))
                columns = list(zip(*got, strict=True)) or [()] * 6
                yield pa.record_batch([batch.column("doc_id").take(pa.array(columns[0], pa.int64())), pa.array(columns[1], pa.string()), pa.array(columns[2], pa.float64()), pa.array(columns[3], pa.int32()), *(pa.array(c, pa.int64()) for c in columns[4:])], [c.split()[0] for c in FOUND.split(", ")])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, FOUND)
