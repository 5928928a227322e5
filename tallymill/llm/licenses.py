"""Licence scans with a trained paragraph classifier.

A multinomial logistic regression on sparse word 1- to 3-grams tells ordinary paragraphs, the
families, and `unknown`: notices of licences that are no family's, and talk of licences that names
none. It is trained on notices written out from templates and on paragraphs of the corpus. Its
temperature, and the probability from which a family is believed, are fitted on notices of
templates and of other licences that a first model has not seen; then it is trained on all. A family
that is less sure is `unknown`; half that probability is enough where the words cover one of its
templates, which confirms it. Of several such families the one of the highest product decides.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import sliced

#: Public licence notices by family.
TEMPLATES: dict[str, list[str]] = {
    "mit": ["MIT License", "the MIT license", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction", "SPDX-License-Identifier: MIT"],
    "apache": ["Apache License, Version 2.0", "the Apache License, Version 2.0", "you may not use this file except in compliance with the License. You may obtain a copy of the License at apache.org/licenses/LICENSE-2.0", "SPDX-License-Identifier: Apache-2.0"],
    "bsd": ["BSD 3-Clause License", "the BSD 2-Clause License", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", "SPDX-License-Identifier: BSD-3-Clause"],
    "gpl": ["GNU General Public License, version 3", "the GNU General Public License as published by the Free Software Foundation, version 2 or any later version", "GNU GPL v3", "SPDX-License-Identifier: GPL-3.0-only"],
    "lgpl": ["GNU Lesser General Public License, version 2.1", "the GNU Lesser General Public License", "SPDX-License-Identifier: LGPL-2.1-or-later"],
    "agpl": ["GNU Affero General Public License, version 3", "the GNU Affero General Public License", "SPDX-License-Identifier: AGPL-3.0-only"],
    "mpl": ["Mozilla Public License, version 2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "SPDX-License-Identifier: MPL-2.0"],
    "cc-by": ["CC BY 4.0", "Creative Commons Attribution 4.0 International License"],
    "cc-by-sa": ["CC BY-SA 4.0", "Creative Commons Attribution-ShareAlike 4.0 International License"],
    "cc-by-nc": ["CC BY-NC 4.0", "Creative Commons Attribution-NonCommercial 4.0 International License"],
    "cc-by-nd": ["CC BY-ND 4.0", "Creative Commons Attribution-NoDerivatives 4.0 International License"],
    "cc0": ["CC0 1.0 Universal", "dedicated to the public domain under CC0", "Creative Commons Zero public domain dedication"],
    "unlicense": ["The Unlicense", "This is free and unencumbered software released into the public domain"],
    "proprietary": ["All rights reserved", "Proprietary and confidential. Unauthorized copying of this file is strictly prohibited"],
}
OPENINGS = ["", "Licensed under {}.", "This work is licensed under {}.", "Released under {}.", "Distributed under the terms of {}.", "This file is part of a project available under {}", "Copyright 2021 the authors. Licensed under {}", "{} applies to this document.", "The text below is published under {}.", "License: {}"]
VERSIONS = ["1.0", "2.0", "2.1", "3.0", "4.0", "v2", "v3"]
NONE, UNKNOWN = "none", "unknown"
#: Paragraphs of the corpus in the training set, as expected by their hash draw.
SAMPLE = 4000
#: Characters of a sampled paragraph that are learned from.
LONGEST = 4000
#: Share of a template's n-grams that confirms its family.
CONFIRM = 0.5
#: Licences that are no family here, and talk of licences that names none.
OTHERS = ["the Eclipse Public License, version 2.0", "the zlib License", "the Artistic License 2.0", "the ISC License", "the Boost Software License, version 1.0", "the European Union Public Licence, version 1.2", "the Microsoft Public License", "the Open Software License 3.0", "the Academic Free License", "the PostgreSQL License", "the SIL Open Font License, version 1.1", "the Common Development and Distribution License", "its own licence", "a licence that we could not find", "the terms in the LICENSE file", "the licence of the publisher"]
TALK = ["See LICENSE for terms.", "License terms apply.", "Please read the licence before use.", "The licence of this text is not known.", "Copyright 2021 the authors.", "Copyright notice", "This material is licensed.", "Use is subject to a license agreement.", "Contact us for licensing.", "License", "SPDX-License-Identifier: ISC", "SPDX-License-Identifier: EPL-2.0", "SPDX-License-Identifier: BSL-1.0"]
#: Ordinary talk in the words of notices, for corpora that have little of it.
ORDINARY = ["The version of this file that we could not find was in the other folder.", "See the table for the terms of the equation.", "This work was released in the spring by the publisher of the journal.", "The text below is part of a project that applies to all of us.", "Use of the file is subject to change by the author.", "Please read the document before use.", "The authors are available under this number at all times.", "It was published by its own authors, not by the foundation.", "Contact us for the material of the course.", "You may not use this room except in the evening.", "The public may visit the open source of the river under any conditions.", "All of the rights and the wrongs of the matter were distributed evenly."]
#: Share of unseen notices of other licences that may be taken for a family.
WRONG = 0.05
_TOKEN = regex.compile(r"[\p{L}\p{N}]+")
_SPEAKS = {"license", "licensed", "licence", "licenced", "licenses", "licensing", "copyright", "spdx", "copyleft", "warranty"}


def tokens(text: str) -> list[str]:
    return _TOKEN.findall(text.lower())


def grams(words: list[str]) -> set[str]:
    return {" ".join(words[k : k + n]) for n in (1, 2, 3) for k in range(len(words) - n + 1)}


def notices(seed: int) -> list[tuple[str, str, bool]]:
    """(class, text, held) of notices written out from the templates and from OTHERS and TALK, with small
    changes; held are all of every third template of a class, unless it has two or less."""
    rng, out = np.random.default_rng(seed), []
    for family, texts in [*TEMPLATES.items(), (UNKNOWN, OTHERS + TALK)]:
        for k, t in enumerate(texts):
            for opening in OPENINGS[:1] if t in TALK else OPENINGS[1:] if t in OTHERS else OPENINGS:
                words = (opening.format(t) if opening else t).split()
                # a short name stays whole: without a word it may be another licence's
                name = t.split() if len(t.split()) <= 10 else []
                free = [i for i, w in enumerate(words) if w.rstrip(".") not in name and w not in name]
                for change in range(3):
                    own = list(words)
                    if change and free:
                        del own[free[int(rng.integers(len(free)))]]
                    out.append((family, " ".join(own), len(texts) > 2 and k % 3 == 1))
    return out


@dataclass
class Model:
    families: list[str]
    bias: np.ndarray
    weights: dict[str, np.ndarray]
    heat: float
    least: float

    def scores(self, words: list[str]) -> np.ndarray:
        known = self.weights
        at = [k for k, w in enumerate(words) if w in known]
        own = {" ".join(words[k : k + n]) for k in at for n in (1, 2, 3) if k + n <= len(words)}
        z = (self.bias + sum((known[g] for g in own if g in known), np.zeros(len(self.bias)))) / self.heat
        e = np.exp(z - z.max())
        return e / e.sum()

    def judge(self, text: str, words: list[str]) -> tuple[str, float, bool] | None:
        """(family, probability, confirmed), or None for an ordinary paragraph."""
        p = self.scores(words)
        best = int(p.argmax())
        family, sure = self.families[best], float(p[best])
        if family == NONE:
            return None
        if family != UNKNOWN:
            # the families whose templates the words cover, weighed by how much of one
            share = covered(words)
            weighed = {f: float(p[self.families.index(f)]) * x for f, x in share.items() if x >= CONFIRM}
            if weighed:
                family = max(weighed, key=weighed.get)
                sure = float(p[self.families.index(family)])
            if sure >= (self.least / 2 if weighed else self.least):
                return family, sure, bool(weighed)
        return UNKNOWN, 1 - float(p[self.families.index(NONE)]), False


_PARTS = {f: [grams(tokens(t)) for t in texts] for f, texts in TEMPLATES.items()}


def covered(words: list[str]) -> dict[str, float]:
    """For each family the largest share of a template's n-grams that stand among words."""
    own = grams(words)
    return {f: max(len(own & t) / len(t) for t in parts) for f, parts in _PARTS.items()}


def _descend(x: np.ndarray, y: np.ndarray, steps: int = 2000, rate: float = 0.5, decay: float = 2e-5) -> tuple[np.ndarray, np.ndarray]:
    w, bias = np.zeros((x.shape[1], y.shape[1]), np.float32), np.zeros(y.shape[1], np.float32)
    vw, vb = np.zeros_like(w), np.zeros_like(bias)
    for _ in range(steps):
        z = x @ w + bias
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        g = (p - y) / np.float32(len(x))
        vw, vb = 0.9 * vw + x.T @ g + decay * w, 0.9 * vb + g.sum(0)
        w, bias = w - rate * vw, bias - rate * vb
    return w, bias


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def fit(docs: DataFrame, sample: int = SAMPLE, seed: int = 42) -> Model:
    """Trains on notices and on about sample / 8 documents' paragraphs of docs(doc_id, text), drawn by
    hash, as ordinary ones; those that speak of a licence are not ordinary and have no label, so they
    are left out. Null texts have none; without documents the notices alone are taken."""
    total = max(1, docs.count())
    share = min(1 << 20, -(-(sample // 8) * (1 << 20) // total))
    drawn = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(1 << 20)) < share).select(F.explode(F.split("text", "\n")).alias("p"))
    plain = drawn.where(F.pmod(F.xxhash64("p"), F.lit(4)) == 0).select(F.substring("p", 1, LONGEST).alias("p")).collect()
    texts = sorted({r[0] for r in plain if not _SPEAKS.intersection(tokens(r[0]))})
    rows = [*notices(seed), *((NONE, t, k % 3 == 1) for k, t in enumerate(texts)), (NONE, "", False), *((NONE, t, False) for t in ORDINARY)]
    families = [NONE, UNKNOWN, *TEMPLATES]
    sets = [grams(tokens(t)) for _, t, _ in rows]
    known = sorted(set().union(*(s for (f, _, _), s in zip(rows, sets) if f != NONE)))
    place = {g: k for k, g in enumerate(known)}
    x = np.zeros((len(rows), len(known)), np.float32)
    for k, s in enumerate(sets):
        x[k, [place[g] for g in s if g in place]] = 1
    truth = np.array([families.index(f) for f, _, _ in rows])
    y, held = np.eye(len(families), dtype=np.float32)[truth], np.array([h for _, _, h in rows])
    w, bias = _descend(x[~held], y[~held])
    z, own = (x @ w + bias)[held], truth[held]

    def loss(heat: float) -> float:
        return float(-np.log(_softmax(z / heat)[np.arange(len(z)), own] + 1e-12).mean())

    heat = min((0.25 * 1.25**k for k in range(20)), key=loss)
    p = _softmax(z / heat)
    # of unseen notices of other licences no more than WRONG reach it for any family
    least = float(np.clip(np.quantile(p[own == families.index(UNKNOWN), 2:].max(1), 1 - WRONG), 0.5, 0.99))
    w, bias = _descend(x, y)
    return Model(families, bias, {g: w[k] for g, k in place.items()}, heat, least)


_FOUND = pa.list_(pa.struct([("place", pa.int32()), ("family", pa.string()), ("probability", pa.float64()), ("confirmed", pa.bool_())]))


def scan(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, found) of every row of docs(doc_id, text): the paragraphs (lines) of found speak
    of a licence, with family or `unknown`, probability and whether a template confirms it. Null and empty
    texts have none; repeated rows come out each; other columns are ignored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bare = model.scores([]).argmax() == 0
        for b in sliced(batches, "text"):
            out = []
            for t in b.column("text").to_pylist():
                found = []
                for k, line in enumerate((t or "").split("\n")):
                    words = tokens(line)
                    # without a known n-gram only the bias speaks
                    if bare and not any(w in model.weights for w in words):
                        continue
                    if said := model.judge(line, words):
                        found.append({"place": k, "family": said[0], "probability": said[1], "confirmed": said[2]})
                out.append(found)
            yield pa.record_batch([b.column("doc_id"), pa.array(out, _FOUND)], names=["doc_id", "found"])

    schema = "doc_id long, found array<struct<place:int,family:string,probability:double,confirmed:boolean>>"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)
