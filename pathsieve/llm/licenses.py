"""License notices: MinHash bands over overlapping text windows, then exact shingle containment."""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pathsieve.llm import kernels as K
from pathsieve.llm.near_dedup import _bijection

SHINGLE, PERCENT, MISS = 5, 80, 1e-6

#: Openings and notices of public licenses, by SPDX identifier.
NOTICES = (
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("LGPL-2.1", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("AGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at"),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software."),
)
#: Licenses as short notices name them, and what comes before.
SHORT = (
    ("MIT", "the MIT License"), ("Apache-2.0", "the Apache License, Version 2.0"), ("BSD-2-Clause", "the BSD 2-Clause License"), ("BSD-3-Clause", "the BSD 3-Clause License"),
    ("GPL-2.0", "the GNU General Public License, version 2"), ("GPL-3.0", "the GNU General Public License, version 3"),
    ("LGPL-2.1", "the GNU Lesser General Public License, version 2.1"), ("LGPL-3.0", "the GNU Lesser General Public License, version 3"),
    ("AGPL-3.0", "the GNU Affero General Public License, version 3"), ("MPL-2.0", "the Mozilla Public License, version 2.0"), ("BSL-1.0", "the Boost Software License, Version 1.0"),
    ("CC-BY-4.0", "CC BY 4.0"), ("CC-BY-NC-4.0", "CC BY-NC 4.0"), ("CC-BY-SA-4.0", "CC BY-SA 4.0"),
    ("CC-BY-4.0", "a Creative Commons Attribution 4.0 International License"), ("CC-BY-NC-4.0", "a Creative Commons Attribution-NonCommercial 4.0 International License"),
    ("CC-BY-SA-4.0", "a Creative Commons Attribution-ShareAlike 4.0 International License"),
)
OPENINGS = ("Released", "Licensed", "Distributed")
TEMPLATES = (*NOTICES, *((name, f"{opening} under {rest}") for name, rest in SHORT for opening in OPENINGS))


class Layer(NamedTuple):
    """Templates of about one length, with the windows that retrieve them."""

    step: int  # shingles between window starts
    steps: int  # steps in a window
    bands: int
    keys: np.ndarray  # (bands, templates) minima
    templates: list[int]
    seen: np.ndarray  # (bands, 65536) lowest 16 bits of the minima


class Plan(NamedTuple):
    names: list[str]
    sets: list[np.ndarray]
    layers: list[Layer]
    percent: int
    tells: list[list[np.ndarray]]


def distinctions(names: list[str], sets: list[np.ndarray], percent: int) -> list[list[np.ndarray]]:
    """For each template, what it has beyond each other license's template that alone holds ``percent`` of it."""
    out = []
    for name, own in zip(names, sets, strict=True):
        rivals = [x for other, x in zip(names, sets, strict=True) if other != name and 100 * np.isin(own, x).sum() >= percent * len(own)]
        out.append([np.setdiff1d(own, x) for x in rivals])
    return out


def bands_for(smallest: int, window: int, percent: int, miss: float = MISS) -> int:
    """Single-row bands so that a window with ``percent`` of a template's shingles is missed with at most ``miss``."""
    held = math.ceil(smallest * percent / 100)
    similarity = held / (window + smallest - held)
    return max(1, math.ceil(math.log(miss) / math.log1p(-min(similarity, 1 - 1e-12))))


def _shingled(texts: pa.Array, k: int):
    data, offsets = K.flat(texts)
    for i, j in K.chunks(offsets):
        b = K.LOWER[data[offsets[i] : offsets[j]]]
        starts, ends, rows = K.words(b, offsets[i : j + 1] - offsets[i], K.ALNUM)
        yield i, j, *K.shingles(K.spans_hash(b, starts, ends), rows, k, whole=False)


def _positions(h: np.ndarray) -> np.ndarray:
    return (K.mix64(h.copy()) >> K.U64(32)).astype(np.uint32)


def plan(templates=TEMPLATES, shingle: int = SHINGLE, percent: int = PERCENT) -> Plan:
    """Templates grouped by length, with each group's windows, bands and keys."""
    sets = []
    for _, text in templates:
        (_, _, h, _), = _shingled(pa.array([text]), shingle)
        if not len(h):
            raise ValueError(f"a template needs {shingle} words: {text!r}")
        sets.append(np.unique(h))
    groups: dict[int, list[int]] = {}
    for t, s in enumerate(sets):
        groups.setdefault(math.ceil(math.log(len(s), 1.5)) if len(s) > 1 else 0, []).append(t)
    layers = []
    for members in groups.values():
        longest, smallest = max(len(sets[t]) for t in members), min(len(sets[t]) for t in members)
        step = max(1, longest // 4)
        steps = -(-(longest + step - 1) // step)
        bands = bands_for(smallest, steps * step, percent)
        keys = np.array([[_bijection(_positions(sets[t]) + np.uint32(k)).min() for t in members] for k in range(bands)], np.uint32)
        seen = np.zeros((bands, 1 << 16), bool)
        seen[np.arange(bands)[:, None], keys & np.uint32(0xFFFF)] = True
        layers.append(Layer(step, steps, bands, keys, members, seen))
    names = [name for name, _ in templates]
    return Plan(names, sets, layers, percent, distinctions(names, sets, percent))


def scan(h: np.ndarray, rows: np.ndarray, p: Plan) -> list[dict[int, float]]:
    """For each row, the templates found and the largest containment seen."""
    found: list[dict[int, float]] = [{} for _ in range(len(rows) - 1)]
    if not len(h):
        return found
    count = np.diff(rows)
    place = _positions(h)
    grids = []
    for layer in p.layers:
        blocks = -(-count // layer.step)
        at = np.concatenate([[0], np.cumsum(blocks)])
        starts = np.repeat(rows[:-1], blocks) + (np.arange(at[-1]) - np.repeat(at[:-1], blocks)) * layer.step
        last = np.repeat(at[1:], blocks)
        grids.append((starts, last, np.zeros((len(starts), 1), bool), [set() for _ in layer.templates]))
    for k in range(max(layer.bands for layer in p.layers)):
        values = _bijection(place + np.uint32(k))
        for layer, (starts, last, _, hits) in zip(p.layers, grids, strict=True):
            if k >= layer.bands:
                continue
            least = np.minimum.reduceat(values, starts)
            window = least.copy()
            index = np.arange(len(least))
            for s in range(1, layer.steps):
                ahead = index + s < last
                window[ahead] = np.minimum(window[ahead], least[index[ahead] + s])
            maybe = np.flatnonzero(layer.seen[k][window & np.uint32(0xFFFF)])
            for x, key in enumerate(layer.keys[k] if len(maybe) else ()):
                hits[x].update(maybe[window[maybe] == key].tolist())
    for layer, (starts, _, _, hits) in zip(p.layers, grids, strict=True):
        for template, windows in zip(layer.templates, hits, strict=True):
            own = p.sets[template]
            for w in sorted(windows):
                row = int(np.searchsorted(rows, starts[w], side="right")) - 1
                part = h[starts[w] : min(starts[w] + layer.step * layer.steps, rows[row + 1])]
                same = int(np.isin(own, part).sum())
                if 100 * same >= p.percent * len(own) and all(np.isin(t, part).any() for t in p.tells[template]):
                    found[row][template] = max(found[row].get(template, 0.0), same / len(own))
    return found


def _scan(batches, p: Plan, shingle: int):
    for batch in batches:
        for i, j, h, rows in _shingled(batch.column("text"), shingle):
            found = scan(h, rows, p)
            names = [sorted({p.names[t] for t in f}) for f in found]
            yield pa.RecordBatch.from_arrays([
                batch.column("doc_id").slice(i, j - i), pa.array(names, pa.list_(pa.string())), pa.array([sorted(f) for f in found], pa.list_(pa.int32())),
                pa.array([max(f.values(), default=0.0) for f in found], pa.float64()),
            ], names=["doc_id", "licenses", "templates", "containment"])


def license_scan(docs: DataFrame, templates=TEMPLATES, shingle: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """Licenses noticed in every row's whole text: doc_id, licenses, templates (numbers in the list), containment (largest).

    Words are runs of ASCII digits, letters (lower-cased) and non-ASCII characters. A template counts as found if some window
    holds ``percent`` of its distinct shingles of ``shingle`` words, and, beside each other license's template that holds as much of it by
    itself, at least one shingle which that one lacks (a version, a name). Windows start every quarter of
    the template group's length from a text's first word and are long enough to hold any place of a template. Single-row bands
    are so many that a window that counts is missed with a probability of at most MISS. Null
    texts, and texts of fewer words than a shingle, have none. The templates are a parameter of bounded size.
    """
    p = plan(templates, shingle, percent)
    id_type = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(lambda it: _scan(it, p, shingle), f"doc_id {id_type}, licenses array<string>, templates array<int>, containment double")
