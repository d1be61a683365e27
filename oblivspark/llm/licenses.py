"""License scans: MinHash bands over overlapping windows retrieve templates, shingle containment verifies them."""

from __future__ import annotations

import math
import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

from .base import column, id_and_text, map_batches, texts_of
from .decontaminate import normal_words

#: Words of a shingle, and the share of a template's shingles that a match holds.
WIDTH, CONTAINED = 5, 0.8
#: A window has room for this share of a template's words beyond it, and for this many at least.
ROOM, LEAST_ROOM = 0.5, 3
#: Least probability with which a window that holds a template retrieves it.
RECALL = 0.9999
#: Shingles that are hashed at a time, small enough for a processor's cache.
BLOCK = 1 << 15
#: Short notices by which licences are declared, under public identifiers.
TEMPLATES = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."],
    "MIT": ["Released under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "BSD": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
    "CC0-1.0": ["To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."],
    "ISC": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."],
    "Zlib": ["This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software."],
    "Unlicense": ["This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."],
    "LGPL-3.0": ["This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation"],
    "CC-BY-4.0": ["This work is licensed under a Creative Commons Attribution 4.0 International License."],
}


def shingle_hashes(texts: list[list[bytes]], width: int) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each run of ``width`` words of each text, one text after the other, and where each text's begin (and the last's end).

    A text of fewer words is one shingle, an empty one none.
    """
    lengths = np.array([len(t) for t in texts], np.int64)
    h = np.array([xxhash.xxh3_64_intdigest(w) for t in texts for w in t], np.uint64)
    out = h.copy()
    runs = np.minimum(lengths, width)
    ends = np.cumsum(lengths)
    starts = ends - lengths
    place = np.arange(len(h)) - np.repeat(starts, lengths)
    run = np.repeat(runs, lengths)
    with np.errstate(over="ignore"):
        for i in range(1, width):
            more = np.zeros_like(h)
            more[: max(0, len(h) - i)] = h[i:]
            mixed = (out ^ (out >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15) + more
            out = np.where(run > i, mixed, out)
    keep = place <= np.repeat(lengths - runs, lengths)
    return out[keep], np.concatenate(([0], np.cumsum(lengths - runs + (lengths > 0))))


def permuted(h: np.ndarray, seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return (h ^ np.uint64(seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)) * np.uint64((seed * 0xBF58476D1CE4E5B9 | 1) & 0xFFFFFFFFFFFFFFFF)


def window_minima(x: np.ndarray, step: int, steps: int) -> np.ndarray:
    """Least of each window of ``steps`` times ``step`` values, one window every ``step`` values; ``len(x)`` is a multiple of ``step``."""
    low = x[::step].copy()
    for i in range(1, step):
        np.minimum(low, x[i::step], out=low)
    n = len(low) - steps + 1
    out = low[:n].copy()
    for i in range(1, steps):
        np.minimum(out, low[i : i + n], out=out)
    return out


def most_contained(h: np.ndarray, shingles: np.ndarray, span: int) -> float:
    """The largest share of the (sorted, distinct) shingles that ``span`` neighbours of ``h`` hold."""
    i = np.minimum(np.searchsorted(shingles, h), len(shingles) - 1)
    at = np.flatnonzero(shingles[i] == h)
    held: dict[int, int] = {}
    best = first = 0
    for p, k in zip(at.tolist(), i[at].tolist()):
        held[k] = held.get(k, 0) + 1
        while at[first] <= p - span:
            out = int(i[at[first]])
            held[out] -= 1
            if not held[out]:
                del held[out]
            first += 1
        best = max(best, len(held))
    return best / len(shingles)


class Scanner:
    """Templates by window length, with as many one-row bands as the asked recall needs.

    A match holds at least k = ceil(c t) of a template's t shingles; a window of w shingles that holds them is at least k / (w + t - k)
    similar to the template, and with b bands of one row it misses the template with probability (1 - similarity) ** b.
    A match's shingles lie within ``stretch`` neighbours; windows begin every ``step`` shingles of each text and have ``step`` - 1 more, so that every such stretch lies within one.
    """

    def __init__(self, templates: dict[str, list[str]], width: int = WIDTH, contained: float = CONTAINED, recall: float = RECALL):
        self.width, self.contained, self.groups = width, contained, {}
        for name, texts in sorted(templates.items()):
            for text in texts:
                words = normal_words(text.encode())
                if words:
                    own, _ = shingle_hashes([words], width)
                    step = max(LEAST_ROOM, int(len(words) * ROOM))
                    stretch = len(own) + step - 1
                    steps = -(-(stretch + step - 1) // step)
                    self.groups.setdefault((step, steps), []).append((name, np.unique(own), stretch))
        self.tables = {}
        for (step, steps), group in self.groups.items():
            similar = 1.0
            for _, own, _ in group:
                k = math.ceil(contained * len(own))
                similar = min(similar, k / (step * steps + len(own) - k))
            bands = max(1, math.ceil(math.log(1 - recall) / math.log(1 - min(similar, 0.999))))
            self.tables[step, steps] = [[permuted(own, b + 1).min() for _, own, _ in group] for b in range(bands)]

    def scan(self, texts: list[bytes]) -> list[dict[str, float]]:
        """For each text the licences found, with the largest share of a template's shingles that one window holds."""
        out: list[dict[str, float]] = [{} for _ in texts]
        h, begin = shingle_hashes([normal_words(t) for t in texts], self.width)
        lengths = np.diff(begin)
        for (step, steps), group in self.groups.items():
            # each text has windows of its own: fillers up to a multiple of ``step``, and a window of them, part it from the next
            span, pairs = step * steps, set()
            room = -(-lengths // step) * step + span
            first = np.cumsum(room) - room
            whole = np.full(int(room.sum()) + span, np.iinfo(np.uint64).max, np.uint64)
            whole[np.repeat(first - begin[:-1], lengths) + np.arange(len(h))] = h
            chunk = max(1, BLOCK // step) * step
            for at in range(0, len(whole) - span, chunk):
                part = whole[at : at + chunk + span - step]
                part = part[: len(part) // step * step]
                blank = part == np.iinfo(np.uint64).max
                for b, keys in enumerate(self.tables[step, steps]):
                    mixed = permuted(part, b + 1)
                    mixed[blank] = np.iinfo(np.uint64).max
                    low = window_minima(mixed, step, steps)
                    for i, key in enumerate(keys):
                        for w in np.flatnonzero(low == key):
                            pairs.add((int(np.searchsorted(first, at + int(w) * step, "right")) - 1, i))
            for d, i in pairs:
                name, own, stretch = group[i]
                share = most_contained(h[begin[d] : begin[d + 1]], own, stretch)
                if share >= self.contained:
                    out[d][name] = max(share, out[d].get(name, 0.0))
        return out


_scanners: dict[str, Scanner] = {}


def license_scan(
    docs: DataFrame, templates: dict[str, list[str]] | None = None, width: int = WIDTH, contained: float = CONTAINED,
    id_col: str = "doc_id", text_col: str = "text",
) -> DataFrame:
    """One row per document: doc_id, n_licenses, licenses (names in order, comma-joined), containment (the largest, 0 if none).

    Words are runs of ASCII letters and digits or wider characters, lower-cased. Each text's shingles lie under
    windows that overlap so far that any stretch that can hold a match lies within one. A window whose least hash equals a template's in
    any band retrieves it for the text (``Scanner`` sets the number of bands); a match holds ``contained`` or more of the template's
    distinct ``width``-word shingles within half as many neighbouring shingles again. What is found in a text doesn't depend on other texts. The templates travel with the task; no exchange.

    Null, empty and wordless texts: no match. A text of fewer than ``width`` words is one shingle. Null or repeated ids: a
    row for each input row. Empty table: no rows. Other columns are ignored.
    """
    templates, name = templates or TEMPLATES, uuid.uuid4().hex
    base = id_and_text(docs, id_col, text_col)

    def kernel(batches):
        if name not in _scanners:
            _scanners.clear()
            _scanners[name] = Scanner(templates, width, contained)
        scan = _scanners[name].scan
        for batch in batches:
            texts, found = texts_of(batch), []
            for at in range(0, len(texts), 256):
                found += scan(texts[at : at + 256])
            yield pa.record_batch(
                [column(batch, "doc_id"), pa.array([len(f) for f in found], pa.int64()), pa.array([",".join(sorted(f)) for f in found]), pa.array([max(f.values(), default=0.0) for f in found])],
                names=["doc_id", "n_licenses", "licenses", "containment"],
            )

    return map_batches(base, kernel, f"doc_id {base.schema['doc_id'].dataType.simpleString()}, n_licenses long, licenses string, containment double")
