"""Licence scan with a trained paragraph classifier.

A paragraph (line) becomes indicators of its word n-grams (one to three words). A softmax regression with an L1 penalty, fitted
by proximal gradient steps, tells licence families, `unknown` (licence language of no family here) and `other` (plain text), and
leaves few n-grams with weight. Its training rows are the templates and foreign notices below in deterministic variations,
legal-sounding decoys, and lines of a bounded sample of the documents, drawn evenly from whole documents. Probabilities are
calibrated by a temperature: it is fitted on variations of templates, notices and lines that the model it is
fitted with never saw. A family counts only if a comparison with its templates confirms it: enough of the
paragraph's trigrams must be in one template, or of a template's in the paragraph; what isn't plain text and has no confirmed
family is `unknown`.

Defined results: null and empty texts have no paragraphs; texts are read whole; repeated rows are scanned alike; an empty
table gives no rows; a paragraph without a word that any weighted n-gram has is plain text, which the model's intercepts say too;
other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import boxed, sliced_texts, table, unboxed
from .decontaminate import words_of

#: Documents whose lines serve as plain text in training, and lines taken of them all, at most.
SAMPLE_DOCS, SAMPLE_LINES = 400, 2000
CONFIDENCE, CONFIRMATION = 0.5, 0.6

# Short notices by which the families are known.
TEMPLATES = {
    "MIT": ["SPDX-License-Identifier: MIT", "Released under the MIT License.", "This project is licensed under the terms of the MIT license.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction", "The software is provided as is, without warranty of any kind, express or implied, including but not limited to the warranties of merchantability"],
    "Apache-2.0": ["SPDX-License-Identifier: Apache-2.0", "Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an as is basis, without warranties or conditions of any kind"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License", "You should have received a copy of the GNU General Public License along with this program."],
    "BSD": ["Licensed under the BSD 3-Clause License.", "Use of this source code is governed by a BSD-style license.", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"],
    "CC-BY": ["This work is licensed under a Creative Commons Attribution 4.0 International License.", "Licensed under CC BY 4.0.", "Content is available under CC BY 4.0 unless otherwise noted."],
    "CC-BY-SA": ["This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.", "Licensed under CC BY-SA 4.0."],
    "CC-BY-NC": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", "Licensed under the Mozilla Public License, version 2.0."],
    "Public-domain": ["This work has been released into the public domain.", "To the extent possible under law, the author has dedicated all copyright to the public domain worldwide under CC0 1.0."],
    "Proprietary": ["All rights reserved.", "Copyright. All rights reserved. No part of this publication may be reproduced without prior written permission of the publisher."],
}
# Notices of licences that are none of the families.
FOREIGN = ["Boost Software License - Version 1.0", "Distributed under the Boost Software License, Version 1.0.", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages", "Licensed under the Eclipse Public License 2.0.", "This program and the accompanying materials are made available under the terms of the Eclipse Public License", "Licensed under the GPLv2 or later.", "Released under the GNU General Public License version 2 only.", "Licensed under the GNU Lesser General Public License, version 2.1.", "Released under the terms of the ISC license.", "Licensed under the zlib license.", "This package is distributed under the Artistic License 2.0.", "Licensed under the European Union Public Licence, version 1.2.", "SPDX-License-Identifier: BSL-1.0", "SPDX-License-Identifier: GPL-2.0-or-later", "This source code is licensed under the license found in the LICENSE file.", "Use of this software is subject to the end user license agreement.", "The contents of this file are subject to the Common Development and Distribution License"]
# Sentences that sound alike and are no licence.
DECOYS = ["The driver renewed a licence at the office.", "A public version of the work was released by the general.", "The terms of the agreement were discussed under the table.", "Permission to enter was granted by the person in charge.", "The software is distributed with a copy of the manual.", "Civil rights were reserved for citizens by law.", "Apache helicopters and a foundation of concrete.", "This program is free for students with a public library card.", "The source of the river was commonly known.", "version 2.0 of the plan was notable"]
FAMILIES = tuple(TEMPLATES)
UNKNOWN, OTHER = len(FAMILIES), len(FAMILIES) + 1


def n_grams(words: list[str], most: int = 3) -> set[str]:
    return {" ".join(words[i : i + n]) for n in range(1, most + 1) for i in range(len(words) - n + 1)}


def tokens(paragraph: str) -> list[str]:
    return [w.decode("utf-8", "replace") for w in words_of(paragraph)]


def variations(words: list[str], n: int, random: np.random.Generator) -> Iterator[list[str]]:
    """A template as found in the wild: words lost, a holder and a year before it, text around it."""
    for k in range(n):
        kept = [w for w in words if len(words) <= 4 or random.random() > 0.06 * (k % 3)]
        head = [[], ["copyright", "c", str(1990 + int(random.integers(40))), "the", "authors"], ["note"]][k % 3]
        yield [*head, *kept]


@dataclass
class LicenceModel:
    index: dict[str, int]
    weights: np.ndarray  # n-grams and the intercept, by class
    temperature: float

    def __post_init__(self) -> None:
        self.anchors = frozenset(w.encode() for g in self.index for w in g.split())
        self.trigrams = [[n_grams(tokens(t), 3) - n_grams(tokens(t), 2) for t in texts] for texts in TEMPLATES.values()]

    def probabilities(self, words: list[str]) -> np.ndarray:
        rows = [self.index[g] for g in n_grams(words) if g in self.index]
        z = (self.weights[rows].sum(0) + self.weights[-1]) / self.temperature
        z = np.exp(z - z.max())
        return z / z.sum()

    def confirmed(self, words: list[str], family: int) -> bool:
        own = n_grams(words, 3) - n_grams(words, 2)
        for of_template in self.trigrams[family]:
            both = len(own & of_template)
            if both and max(both / len(own), both / len(of_template)) >= CONFIRMATION:
                return True
        return False

    def judge(self, paragraph: str) -> tuple[str, float] | None:
        """Family or `unknown` with its probability; None for plain text."""
        words = tokens(paragraph)
        p = self.probabilities(words)
        if p[OTHER] >= 0.5:
            return None
        best = int(p[:UNKNOWN].argmax())
        if p[best] >= CONFIDENCE and self.confirmed(words, best):
            return FAMILIES[best], float(p[best])
        return "unknown", float(1 - p[OTHER])

    def scan(self, text: str | None) -> tuple[int, list[tuple[str, float, int]]]:
        """Number of paragraphs, and (family, probability, paragraph number) of those that aren't plain text."""
        lines = [x for x in (text or "").split("\n") if x.strip()]
        found = []
        if lines and not self.anchors.isdisjoint(words_of(text)):
            for k, line in enumerate(lines):
                if not self.anchors.isdisjoint(words_of(line)) and (got := self.judge(line)):
                    found.append((*got, k))
        return len(lines), found


def largest_square(x: np.ndarray, steps: int = 60) -> float:
    """Square of the largest singular value of a nonnegative matrix, by power steps from the row sums."""
    v = x.T @ x.sum(1)
    for _ in range(steps):
        v = x.T @ (x @ (v / max(np.linalg.norm(v), 1e-300)))
    return float(np.linalg.norm(v))


def softmax_l1(x: np.ndarray, y: np.ndarray, classes: int, penalty: float = 2e-4, steps: int = 400) -> np.ndarray:
    """Weights by accelerated proximal gradient; the intercepts (last row) are not penalised. Equal rows count as one with a weight."""
    n = len(x)
    _, first, counts = np.unique(np.hstack([np.packbits(x > 0, axis=1), y[:, None].astype(np.uint8)]), axis=0, return_index=True, return_counts=True)
    x, target, share = np.hstack([x[first], np.ones((len(first), 1))]).astype(float), np.eye(classes)[y[first]], counts[:, None] / n
    rate = 4 / max(1.0 / n, largest_square(x * np.sqrt(share)))
    w = z = np.zeros((x.shape[1], classes))
    momentum = 1.0
    for _ in range(steps):
        s = x @ z
        p = np.exp(s - s.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        new = z - rate * (x.T @ ((p - target) * share))
        new[:-1] = np.sign(new[:-1]) * np.maximum(np.abs(new[:-1]) - rate * penalty, 0)
        following = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        z = new + (momentum - 1) / following * (new - w)
        w, momentum = new, following
    return w


def sample_lines(docs: DataFrame, docs_limit: int, lines_limit: int) -> list[str]:
    """Lines of a bounded number of documents: documents by a hash of the id, lines by a hash of id and place, whole lines."""
    # Ids are chosen first: only the chosen documents are cut into lines, however many tasks there are.
    chosen = docs.select("doc_id").filter("text IS NOT NULL AND doc_id IS NOT NULL").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(docs_limit)
    lines = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id").select("doc_id", F.posexplode(F.split("text", "\n")).alias("k", "line")).filter("trim(line) <> ''")
    return [r["line"] for r in lines.orderBy(F.xxhash64("doc_id", "k"), "doc_id", "k", "line").limit(lines_limit).collect()]


def fit_licences(docs: DataFrame, docs_limit: int = SAMPLE_DOCS, lines_limit: int = SAMPLE_LINES) -> LicenceModel:
    """Templates, foreign notices, decoys and sampled lines; only n-grams of templates and notices that plain lines lack count."""
    random = np.random.default_rng(5)
    sources = [(k, tokens(t)) for k, texts in enumerate([*TEMPLATES.values(), FOREIGN]) for t in texts]
    # A line that is (nearly) a template must not teach the model that it is plain text.
    known = [n_grams(words, 2) for _, words in sources]
    plain = []
    for line in sample_lines(docs, docs_limit, lines_limit):
        words = tokens(line)
        own = n_grams(words, 2)
        if words and max(len(own & k) / len(k) for k in known) < 0.4:
            plain.append(words)
    # The held part: the last template of each family that has three, each fourth notice, decoy and line.
    rows, labels, held = [], [], []

    def add(words: list[str], label: int, apart: bool) -> None:
        rows.append(n_grams(words))
        labels.append(label)
        held.append(apart)

    for k, words in sources:
        own = [w for c, w in sources if c == k]
        apart = (k < UNKNOWN and len(own) > 2 and words is own[-1]) or (k == UNKNOWN and own.index(words) % 4 == 3)
        for varied in variations(words, 12, random):
            add(varied, k, apart)
    candidates: dict[str, int] = {}
    for grams in rows:
        for g in sorted(grams):
            candidates.setdefault(g, 0)
    for words in plain:
        for g in n_grams(words) & candidates.keys():
            candidates[g] += 1
    index = {g: k for k, g in enumerate(g for g, n in candidates.items() if n <= max(1, len(plain) // 500))}
    for repeat in range(6):
        for k, d in enumerate(DECOYS):
            add(tokens(d), OTHER, k % 4 == 3 and repeat == 0)
    for k, words in enumerate(plain):
        add(words, OTHER, k % 4 == 3)
    x = np.zeros((len(rows), len(index)), np.float32)
    for i, grams in enumerate(rows):
        x[i, [index[g] for g in grams & index.keys()]] = 1
    y, held = np.array(labels), np.array(held)
    part = softmax_l1(x[~held], y[~held], OTHER + 1)
    z = np.hstack([x[held], np.ones((held.sum(), 1))]) @ part
    losses = []
    for t in (0.5, 0.7, 1.0, 1.4, 2.0, 2.8):
        s = z / t - (z / t).max(1, keepdims=True)
        losses.append((-(s[np.arange(len(s)), y[held]] - np.log(np.exp(s).sum(1))).mean(), t))
    w = softmax_l1(x, y, OTHER + 1)
    used = np.flatnonzero(np.abs(w[:-1]).max(1) > 0)
    names = list(index)
    return LicenceModel({names[i]: k for k, i in enumerate(used.tolist())}, np.vstack([w[used], w[-1:]]), min(losses)[1])


def scan_licences(docs: DataFrame, model: LicenceModel, keep: list[str], text_col: str = "text") -> DataFrame:
    """row (the kept columns), n_paragraphs, found (family, probability, paragraph): one scan, no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    item = pa.struct([("family", pa.string()), ("probability", pa.float64()), ("paragraph", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in sliced_texts(batches, "text"):
            counts, found = zip(*(m.scan(t) for t in batch.column("text").to_pylist()), strict=True)
            rows = [[{"family": f, "probability": p, "paragraph": k} for f, p, k in x] for x in found]
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(counts, pa.int32()), pa.array(rows, pa.list_(item))], ["row", "n_paragraphs", "found"])

    chosen = boxed(docs, keep, text_col)
    one = T.StructType().add("family", "string").add("probability", "double").add("paragraph", T.IntegerType())
    return chosen.mapInArrow(run, chosen.select("row").schema.add("n_paragraphs", T.IntegerType()).add("found", T.ArrayType(one)))


def op2_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = scan_licences(docs, fit_licences(docs), ["doc_id"])
    families = F.array_sort(F.array_distinct(F.transform("found", lambda f: f["family"])))
    return unboxed(found, "n_paragraphs", F.array_join(families, ",").alias("licences"), F.size("found").alias("n_matches"), F.coalesce(F.array_max(F.transform("found", lambda f: f["probability"])), F.lit(0.0)).alias("best_probability"))
