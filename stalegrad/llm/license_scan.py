"""License notices found by MinHash bands over overlapping windows, verified by containment.

For every template length a text is read through overlapping windows of that
many tokens, an eighth of the length apart (at least one token).  Band hashes of
a window's shingle set retrieve templates of that length.  A notice that meets
``percent`` at its own place stands at most half a step from some window, which
then shares at least as many shingles less that distance; the bands of a length
are so many that a window with the least resemblance this allows is missed with
probability ``MISS`` at most.  A retrieved template is verified at every start of
the text: it counts if at least ``percent`` in a hundred of its shingles stand in
a window of its length, on exact sets.

A window without any template shingle cannot share a band with a template, so
only windows that hold one are signed; that skips nearly all text without
changing a result.

Edge cases: null and empty texts have no notice; texts shorter than a template
form one window; repeated rows each give their rows; an empty template list
gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.decontaminate import token_column, token_hashes, token_text
from stalegrad.llm.kernels import U64, mix

SHINGLE, PERCENT = 3, 80
MISS = 1e-9
_FILTER = 1 << 20

#: Public license notices, as short lines, headers, grants and conditions.
TEMPLATES = {
    "apache-2.0/line": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0/header": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at',
    "apache-2.0/warranty": 'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.',
    "mit/line": "Released under the MIT License.",
    "mit/grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction',
    "mit/rights": "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "mit/notice": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "mit/warranty": 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "gpl-2.0/line": "This work is licensed under the GNU General Public License, version 2.",
    "gpl-3.0/line": "This work is licensed under the GNU General Public License, version 3.",
    "gpl/header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "gpl/warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "gpl/copy": "You should have received a copy of the GNU General Public License along with this program. If not, see",
    "lgpl/header": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation",
    "lgpl/copy": "You should have received a copy of the GNU Lesser General Public License along with this library",
    "agpl/header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation",
    "agpl/copy": "You should have received a copy of the GNU Affero General Public License along with this program. If not, see",
    "bsd-3-clause/head": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "bsd/source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd/binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd-3-clause/endorse": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "bsd-4-clause/advertising": "All advertising materials mentioning features or use of this software must display the following acknowledgement:",
    "bsd/warranty": 'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES',
    "mpl-2.0/header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "mpl-2.0/copy": "If a copy of the MPL was not distributed with this file, You can obtain one at",
    "isc/grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
    "isc/notice": "provided that the above copyright notice and this permission notice appear in all copies.",
    "isc/warranty": 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.',
    "zlib/warranty": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.",
    "zlib/grant": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "boost-1.0/line": "Distributed under the Boost Software License, Version 1.0.",
    "epl-2.0/header": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at",
    "cc-by-4.0/line": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc-by-sa-4.0/line": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "cc-by-nc-4.0/line": "Licensed under CC BY-NC 4.0.",
    "cc-by-nc-4.0/long": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "cc-by-nd-4.0/line": "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License.",
    "cc-by-nc-sa-4.0/line": "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License.",
    "cc0-1.0/line": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "unlicense/head": "This is free and unencumbered software released into the public domain.",
    "unlicense/grant": "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "wtfpl-2/line": "This program is free software. It comes without any warranty, to the extent permitted by applicable law.",
    "all-rights-reserved/line": "All rights reserved. No part of this publication may be reproduced, distributed, or transmitted in any form or by any means without the prior written permission of the publisher.",
}


def shingles(tokens: np.ndarray) -> np.ndarray:
    n = len(tokens)
    if not n:
        return np.zeros(0, dtype=np.uint64)
    size = min(SHINGLE, n)
    out = np.zeros(n - size + 1, dtype=np.uint64)
    for j in range(size):
        out = out * U64(0x9E3779B97F4A7C15) + tokens[j : n - size + 1 + j]
    return mix(out + U64(size))


@dataclass
class Bands:
    """Windows of one length: their step, the salts of their bands, and the templates by band hash."""

    step: int
    salts: np.ndarray
    table: dict[int, list[str]] = field(default_factory=dict)

    def keys(self, distinct: np.ndarray) -> list[int]:
        """Band hashes of one shingle set."""
        low = mix(distinct[:, None, None] ^ self.salts[None]).min(axis=0)
        key = np.arange(len(low), dtype=np.uint64)
        for j in range(low.shape[1]):
            key = mix(key * U64(0x9E3779B97F4A7C15) + low[:, j])
        return key.tolist()


def plan_bands(length: int, sizes: list[int], percent: int) -> Bands:
    """Step and bands that find templates of ``length`` tokens and of so many distinct shingles at any offset."""
    inside = max(1, length - SHINGLE + 1)
    needs = [max(1, -(-percent * m // 100)) for m in sizes]
    step = max(1, min(length // 8, *needs))
    left = [need - step // 2 for need in needs]
    least = min(x / (m + inside - x) for x, m in zip(left, sizes, strict=True))
    rows = 2 if least >= 0.4 else 1
    count = 1 if least >= 1 else math.ceil(math.log(MISS) / math.log1p(-(least**rows)))
    return Bands(step, np.random.default_rng(31).integers(1, 2**63, (count, rows), dtype=np.uint64))


class Templates:
    """Shingle sets of the templates, their bands by length, and a filter of their shingles."""

    def __init__(self, texts: dict[str, str], percent: int = PERCENT):
        self.percent = percent
        self.sets: dict[str, np.ndarray] = {}
        self.filter = np.zeros(_FILTER, dtype=bool)
        names = sorted(texts)
        lengths: dict[int, list[str]] = {}
        for i, tokens in token_hashes(pa.array([token_text(texts[n] or "") for n in names], pa.string())):
            if not len(tokens):
                continue
            own = np.unique(shingles(tokens))
            self.sets[names[i]] = own
            self.filter[(own & U64(_FILTER - 1)).astype(np.int64)] = True
            lengths.setdefault(len(tokens), []).append(names[i])
        self.bands = {length: plan_bands(length, [len(self.sets[n]) for n in group], percent) for length, group in lengths.items()}
        for length, group in lengths.items():
            for name in group:
                for b in self.bands[length].keys(self.sets[name]):
                    self.bands[length].table.setdefault(b, []).append(name)
        self.every = np.unique(np.concatenate(list(self.sets.values()))) if self.sets else np.zeros(0, dtype=np.uint64)

    def scan(self, tokens: np.ndarray) -> list[tuple[str, int, int, int, int]]:
        """(template, first token, tokens, shared, template shingles): the best window of each template."""
        line = shingles(tokens)
        if not len(line) or not len(self.every):
            return []
        hot = np.flatnonzero(self.filter[(line & U64(_FILTER - 1)).astype(np.int64)])
        hot = hot[self.every[np.minimum(np.searchsorted(self.every, line[hot]), len(self.every) - 1)] == line[hot]]
        if not len(hot):
            return []
        best: dict[str, tuple[int, int, int]] = {}
        for length, bands in self.bands.items():
            size = min(length, len(tokens))
            inside = max(1, size - SHINGLE + 1)
            starts = np.arange(0, len(tokens) - size + 1, bands.step)
            if starts[-1] != len(tokens) - size:
                starts = np.append(starts, len(tokens) - size)
            starts = starts[np.searchsorted(hot, starts) < np.searchsorted(hot, starts + inside)]
            met = {name for s in starts.tolist() for b in bands.keys(np.unique(line[s : s + inside])) for name in bands.table.get(b, ())}
            for name in met:
                shared = _shared(line, hot, self.sets[name], inside, len(tokens) - size + 1)
                s = int(shared.argmax())
                if shared[s] and 100 * int(shared[s]) >= self.percent * len(self.sets[name]):
                    best[name] = (s, size, int(shared[s]))
        return [(name, *best[name], len(self.sets[name])) for name in sorted(best)]


def _shared(line: np.ndarray, hot: np.ndarray, own: np.ndarray, inside: int, count: int) -> np.ndarray:
    """How many distinct shingles of ``own`` stand in each of the windows that start at 0..count-1."""
    at = hot[np.isin(line[hot], own)]
    order = np.lexsort((at, line[at]))
    before = np.full(len(at), -1)
    again = np.flatnonzero(line[at[order]][1:] == line[at[order]][:-1]) + 1
    before[order[again]] = at[order[again - 1]]
    # a place counts for the starts that reach it and lie behind the place before with the same shingle
    first = np.maximum(np.maximum(before, at - inside) + 1, 0)
    change = np.zeros(max(len(line), count) + 1, dtype=np.int64)
    np.add.at(change, first, 1)
    np.add.at(change, at + 1, -1)
    return np.cumsum(change)[:count]


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, percent: int = PERCENT) -> DataFrame:
    """doc_id, template, license, first_token, n_tokens, n_shared, n_template: one row a document and template.

    The template list is the caller's, a few hundred texts at most, and travels
    with the task.
    """
    texts = TEMPLATES if templates is None else templates
    shared = docs.sparkSession.sparkContext.broadcast(texts)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = Templates(shared.value, percent)
        for batch in batches:
            ids = batch.column("doc_id")
            rows = [(ids[i].as_py(), name, name.split("/")[0], *rest) for i, doc in token_hashes(batch.column("tokens")) for name, *rest in table.scan(doc)]
            if rows:
                kinds = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["doc_id", "template", "license", "first_token", "n_tokens", "n_shared", "n_template"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), token_column(F.col("text")).alias("tokens")).mapInArrow(read, "doc_id long, template string, license string, first_token long, n_tokens long, n_shared long, n_template long")
