"""Licence scans with a trained paragraph classifier.

Paragraphs (lines; long lines in overlapping windows) become sparse hashed word
1-, 2- and 3-grams.  A multinomial logistic regression over them, trained here on
public notice templates with random edits and on ordinary paragraphs of a bounded
sample, names a licence family or the unknown class; its temperature and the
threshold under which a family becomes unknown are calibrated on rows kept from
the fit.  A prediction stands only when the paragraph also holds enough of the
word pairs of one of the family's templates.

The sample is bounded by parameters: SAMPLE_DOCS documents of under SAMPLE_BYTES
bytes, and of them PLAIN_MOST paragraphs; scanning covers all texts.

Defined cases: null, empty and blank texts have no paragraph; a document without
a confirmed notice has no family; texts of any length are scanned whole; rows that
repeat are reported alike; further columns, whatever their names, are not read; an
empty table gives no rows, and an empty sample trains on the templates alone.
"""

from __future__ import annotations

import random
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .tiling import token_words

GRAM_BITS, GRAMS = 15, 3
WINDOW, STRIDE = 64, 32
PLAIN_MOST = 800  # ordinary paragraphs of the sample that are trained on
SAMPLE_DOCS, SAMPLE_BYTES = 300, 20_000  # documents whose paragraphs serve as ordinary text, and their size
CONTAINED = 0.5  # share of a template's word pairs, or of the paragraph's, that confirms
VARIANTS = 30
UNKNOWN = "unknown"
ANCHORS = "licens licenc copyright spdx warranty redistribut permission granted"

# fixed values: public notices and their families
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "This project is licensed under the terms of the MIT license. SPDX-License-Identifier: MIT"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("GPL", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL", "SPDX-License-Identifier: GPL-3.0-or-later"),
    ("LGPL", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation"),
    ("AGPL", "Licensed under the GNU Affero General Public License, version 3."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("BSD", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-NC", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY", "Licensed under CC BY 4.0."),
    ("CC-BY", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License. CC BY-SA 4.0"),
    ("CC0", "To the extent possible under law, the author has waived all copyright and related rights to this work. CC0 1.0 Universal public domain dedication"),
    ("CC-BY-ND", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License. CC BY-ND 4.0"),
    ("MIT", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("BSD", "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES ARE DISCLAIMED"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software."),
    ("EPL", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0"),
    ("BSL-1.0", "Distributed under the Boost Software License, Version 1.0."),
    ("CDDL", "The contents of this file are subject to the terms of the Common Development and Distribution License. You may not use this file except in compliance with the License."),
    ("EUPL", "Licensed under the EUPL, Version 1.2 or, as soon they will be approved by the European Commission, subsequent versions of the EUPL"),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software"),
    ("proprietary", "All rights reserved."),
    ("proprietary", "Copyright (c) 2020 The Authors. All rights reserved."),
    ("proprietary", "Copyright. All rights reserved. No part of this publication may be reproduced or distributed without prior written permission."),
)
# fixed values: ordinary sentences that use the words of notices
DECOYS = (
    "the driver lost his license after the accident", "a fishing license costs ten dollars a year", "the license plate of the car was dirty",
    "copyright law is taught in the second year", "the general public was invited to the version of the play", "work under pressure requires free time",
    "the public library is free for all", "the foundation published its report", "source and binary star systems", "she was granted permission to leave early",
)


def paragraphs(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(token hashes, bounds (start, stop) of each piece, text of each piece)."""
    texts, words = token_words(column)
    hashes = words.hashes()
    if not len(hashes):
        return hashes, np.zeros((0, 2), np.int64), np.zeros(0, np.int64)
    doc = np.repeat(np.arange(len(texts.offs) - 1), np.diff(words.first))
    lines = np.concatenate([[0], np.cumsum(texts.data == 10, dtype=np.int64)])[words.starts]
    new = np.append(True, (np.diff(lines) != 0) | (np.diff(doc) != 0))
    starts = np.flatnonzero(new)
    stops = np.append(starts[1:], len(hashes))
    # a line longer than a window becomes windows that overlap
    counts = np.maximum(1, -(-(stops - starts - WINDOW) // STRIDE) + 1)
    base = np.repeat(starts, counts)
    nth = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    a = base + nth * STRIDE
    b = np.minimum(a + WINDOW, np.repeat(stops, counts))
    return hashes, np.stack([a, b], axis=1), doc[a]


def gram_ids(hashes: np.ndarray, n: int) -> np.ndarray:
    return (K.chained(hashes, n) >> np.uint64(64 - GRAM_BITS)).astype(np.int64)


def _span_sums(table: np.ndarray, ids: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Rows of ``table`` at ids[a:b], summed for each span (zero for an empty one)."""
    out = np.zeros((len(a), table.shape[1]), table.dtype)
    full = np.flatnonzero(b > a)
    if len(full):
        cuts = np.stack([a[full], b[full]], axis=1).ravel()
        rows = np.concatenate([table[ids], np.zeros((1, table.shape[1]), table.dtype)])
        out[full] = np.add.reduceat(rows, cuts, axis=0)[::2]
    return out


@dataclass
class LicenceModel:
    families: list[str]
    table: np.ndarray  # gram -> family logits; the last column is the unknown class
    bias: np.ndarray
    temperature: float
    threshold: float
    pairs: list[tuple[int, np.ndarray]]  # (family, word pairs of a template)

    def logits(self, hashes: np.ndarray, spans: np.ndarray) -> np.ndarray:
        total = np.zeros((len(spans), self.table.shape[1]), np.float32)
        size = np.zeros(len(spans))
        for n in range(1, GRAMS + 1):
            stops = np.maximum(spans[:, 0], spans[:, 1] - n + 1)
            total += _span_sums(self.table, gram_ids(hashes, n), spans[:, 0], stops)
            size += stops - spans[:, 0]
        return total / np.sqrt(np.maximum(1, size))[:, None] + self.bias

    def classify(self, hashes: np.ndarray, spans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(family index or -1, probability) by the classifier alone."""
        z = self.logits(hashes, spans) / self.temperature
        z = np.exp(z - z.max(axis=1, keepdims=True))
        p = z / z.sum(axis=1, keepdims=True)
        best = p[:, :-1].argmax(axis=1)
        top = p[np.arange(len(p)), best]
        return np.where(top >= self.threshold, best, -1), top

    def confirm(self, family: int, tokens: np.ndarray) -> float:
        """Best share of a template's word pairs held by the tokens (or of theirs by the template, if shorter)."""
        own = np.unique(K.chained(tokens, 2))
        best = 0.0
        for k, pairs in self.pairs:
            if k == family and len(pairs) and len(own):
                common = len(np.intersect1d(own, pairs, True))
                best = max(best, common / min(len(pairs), max(len(own), 3)))
        return best


def _variants(text: str, rng: random.Random):
    words = text.split()
    yield text
    for _ in range(VARIANTS):
        out = [w for w in words if rng.random() > 0.08] or words
        if rng.random() < 0.3:
            out = out[: max(3, int(len(out) * rng.uniform(0.5, 1)))]
        if rng.random() < 0.4:
            out = [f"{rng.choice(['Copyright', '(c)', 'Author', 'Note'])}", str(rng.randrange(1990, 2030)), *out]
        if rng.random() < 0.3:
            out.insert(rng.randrange(len(out) + 1), f"w{rng.randrange(1000)}")
        yield " ".join(out)


def fit(documents: DataFrame, sample_docs: int = SAMPLE_DOCS) -> LicenceModel:
    """Train on the templates and on ordinary paragraphs of at most ``sample_docs`` documents of under SAMPLE_BYTES bytes."""
    rng = random.Random(11)
    families = sorted({f for f, _ in TEMPLATES})
    pieces, target = [], []
    for family, text in TEMPLATES:
        for v in _variants(text, rng):
            pieces.append(v)
            target.append(families.index(family))
    sample = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(F.octet_length("text") < SAMPLE_BYTES)
    # a hash picks about 1.5 times as many rows as wanted, so no task sends more than its share
    share = min(1.0, 1.5 * sample_docs / max(1, documents.count()))
    picked = sample.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(share * (1 << 30)))
    rows = sorted(picked.collect(), key=lambda r: (r.doc_id is None, hash_of(str(r.doc_id)), r.text))[:sample_docs]
    plain = [line for r in rows for line in r.text.split("\n") if line.strip() and not any(a in line.lower() for a in ANCHORS.split())]
    plain = sorted(plain, key=lambda s: hash_of(s))[:PLAIN_MOST]
    mixed = " ".join(t for _, t in TEMPLATES).split()
    for text in [*plain, *DECOYS * 8, *(" ".join(rng.choice(mixed) for _ in range(rng.randrange(3, 30))) for _ in range(300))]:
        pieces.append(text)
        target.append(len(families))
    hashes, spans, owner = paragraphs(pa.array([p.replace("\n", " ") for p in pieces], pa.string()))
    y = np.array(target)[owner]
    counts = [(gram_ids(hashes[a:b], n)) for a, b in spans for n in range(1, GRAMS + 1)]
    rows_of = np.repeat(np.arange(len(spans)).repeat(GRAMS), [len(c) for c in counts])
    cols = np.concatenate(counts)
    used, cols = np.unique(cols, return_inverse=True)
    size = np.bincount(rows_of, minlength=len(spans))
    value = (1 / np.sqrt(np.maximum(1, size)))[rows_of].astype(np.float32)
    held = np.arange(len(spans)) % 5 == 0
    w, b = np.zeros((len(used), len(families) + 1), np.float32), np.zeros(len(families) + 1, np.float32)
    onehot = np.eye(len(families) + 1, dtype=np.float32)[y]
    weight = (~held / np.bincount(y, minlength=len(families) + 1).clip(1)[y] ** 0.5)[:, None]
    weight = (weight / weight.sum()).astype(np.float32)
    order = np.argsort(cols, kind="stable")
    rows_by_gram, value_by_gram = rows_of[order], value[order][:, None]
    heads = np.flatnonzero(np.diff(cols[order], prepend=-1))
    starts = np.searchsorted(rows_of, np.arange(len(spans)))
    some = size > 0
    vel_w, vel_b = np.zeros_like(w), np.zeros_like(b)

    def forward():
        z = np.zeros((len(spans), w.shape[1]), np.float32)
        z[some] = np.add.reduceat(w[cols] * value[:, None], starts[some], axis=0)
        return z + b

    for _ in range(100):
        z = forward()
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        g = (p - onehot) * weight
        gw = np.add.reduceat(g[rows_by_gram] * value_by_gram, heads, axis=0) + 1e-6 * w
        vel_w, vel_b = 0.9 * vel_w - 40 * gw, 0.9 * vel_b - 4 * g.sum(0)
        w, b = w + vel_w, b + vel_b
    z, label = forward()[held], y[held]
    grid = np.exp(np.linspace(np.log(0.2), np.log(5), 41))
    losses = []
    for t in grid:
        q = z / t
        q = q - q.max(1, keepdims=True)
        losses.append(-np.mean(q[np.arange(len(q)), label] - np.log(np.exp(q).sum(1))))
    temperature = float(grid[int(np.argmin(losses))])
    p = np.exp(z / temperature - (z / temperature).max(1, keepdims=True))
    p /= p.sum(1, keepdims=True)
    top = p[:, :-1].max(1)
    # least threshold at which 99 of 100 kept ordinary paragraphs are unknown
    ordinary = np.sort(top[label == len(families)])
    threshold = float(min(0.9, max(0.3, ordinary[int(0.99 * (len(ordinary) - 1))] if len(ordinary) else 0.3)))
    table = np.zeros((1 << GRAM_BITS, w.shape[1]), np.float32)
    table[used] = w
    pairs = []
    for family, text in TEMPLATES:
        pairs.append((families.index(family), np.unique(K.chained(token_words(pa.array([text]))[1].hashes(), 2))))
    return LicenceModel(families, table, b.astype(np.float32), temperature, threshold, pairs)


def hash_of(text: str) -> int:
    import zlib

    return zlib.crc32(text.encode())


RESULT = "doc_id long, n_paragraphs long, n_notices long, families string, best_probability double, best_containment double"


def _scan(model: LicenceModel):
    def run(batches):
        for batch in K.chunks(batches, "text"):
            n = batch.num_rows
            hashes, spans, doc = paragraphs(batch.column(1))
            family, prob = model.classify(hashes, spans) if len(spans) else (np.zeros(0, np.int64), np.zeros(0))
            notes, hits, best, held = [set() for _ in range(n)], np.zeros(n, np.int64), np.zeros(n), np.zeros(n)
            for i in np.flatnonzero(family >= 0).tolist():
                share = model.confirm(int(family[i]), hashes[spans[i, 0] : spans[i, 1]])
                if share >= CONTAINED:
                    d = doc[i]
                    notes[d].add(model.families[family[i]])
                    hits[d] += 1
                    best[d], held[d] = max(best[d], prob[i]), max(held[d], share)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(np.bincount(doc, minlength=n).astype(np.int64)), pa.array(hits), pa.array([",".join(sorted(s)) or None for s in notes], pa.string()), pa.array(best), pa.array(held)],
                names=[f.split()[0] for f in RESULT.split(", ")],
            )

    return run


def scan(documents: DataFrame, model: LicenceModel | None = None) -> DataFrame:
    """One row a document: its pieces, confirmed notices and their families."""
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(_scan(model or fit(docs)), RESULT)


def op4_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licence notices of all documents."""
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
