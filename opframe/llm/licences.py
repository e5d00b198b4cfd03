"""Licence scans by a trained paragraph classifier (operator 10).

Word windows and paragraphs (lines with a word) become sparse presence vectors of hashed word
n-grams. Windows are as long as a template and lie where its two-word grams are found, so that a
notice is seen inside a long line or across single line ends as if it stood alone. A logistic regression per licence family, trained on notices written out from templates and on
paragraphs of the corpus as the unknown class, proposes a family; its probability is calibrated
on notices and paragraphs kept aside, and what is under the bar is unknown. A proposal counts
only if it also resembles one of the family's templates. Of overlapping windows the likest counts.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import buffers, byte_table, hash_words, mix, pieces, ragged, words
from .learning import calibrate, drawn, fit_logistic

#: Families and notices that stand for them; {v} is a version, {y} a year, {n} a name. Fixed values.
TEMPLATES: dict[str, list[str]] = {
    "MIT": [
        "Released under the MIT License.",
        "Licensed under the MIT License.",
        "This project is licensed under the terms of the MIT license.",
        "SPDX-License-Identifier: MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software",
    ],
    "Apache": [
        "Licensed under the Apache License, Version {v}.",
        "Licensed under the Apache License, Version {v} (the \"License\"); you may not use this file except in compliance with the License.",
        "Released under the Apache License {v}.",
        "SPDX-License-Identifier: Apache-{v}",
    ],
    "GPL": [
        "This work is licensed under the GNU General Public License, version {v}.",
        "Licensed under the GNU General Public License, version {v} or later.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License",
        "SPDX-License-Identifier: GPL-{v}-or-later",
    ],
    "LGPL": [
        "This library is licensed under the GNU Lesser General Public License, version {v}.",
        "SPDX-License-Identifier: LGPL-{v}-only",
    ],
    "BSD": [
        "Redistribution and use in source and binary forms, with or without modification, are permitted",
        "Released under the BSD 3-Clause License.",
        "Licensed under the BSD 2-Clause License.",
        "SPDX-License-Identifier: BSD-3-Clause",
    ],
    "MPL": [
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. {v}.",
        "Licensed under the Mozilla Public License, version {v}.",
        "SPDX-License-Identifier: MPL-{v}",
    ],
    "CC-BY": [
        "Licensed under CC BY {v}.",
        "This work is licensed under a Creative Commons Attribution {v} International License.",
        "SPDX-License-Identifier: CC-BY-{v}",
    ],
    "CC-BY-NC": [
        "Licensed under CC BY-NC {v}.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial {v} International License.",
        "SPDX-License-Identifier: CC-BY-NC-{v}",
    ],
    "CC-BY-SA": [
        "Licensed under CC BY-SA {v}.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike {v} International License.",
        "SPDX-License-Identifier: CC-BY-SA-{v}",
    ],
    "CC0": [
        "Released into the public domain under CC0 {v}.",
        "To the extent possible under law, the author has waived all copyright and related rights to this work (CC0).",
        "SPDX-License-Identifier: CC0-{v}",
    ],
    "Proprietary": [
        "Copyright {y} {n}. All rights reserved.",
        "All rights reserved.",
        "All rights reserved. No part of this work may be reproduced without permission.",
        "Confidential and proprietary. Unauthorised copying of this file is strictly prohibited.",
    ],
}
#: Buckets (log2), n-gram sizes, bound of unknown paragraphs, bars on probability and on template likeness.
BITS, GRAMS, MOST_UNKNOWN, BAR, LIKENESS = 14, (1, 2, 3), 2000, 0.5, 0.6
#: Bounds of the sampled texts and their bytes; characters of a corpus paragraph that some written notices go on with; near misses have licence words but less than this likeness.
MOST_TEXTS, MOST_BYTES, TAIL, MISS = 400, 16 << 20, 60, 0.4
#: Share of a template's two-word grams that proposes a window; words by which parts of a notice may be shifted.
PROPOSE, SLACK = 0.4, 3
_WORDS = byte_table([x for x in range(128) if not (48 <= x < 58 or 65 <= x < 91 or 97 <= x < 123)])
_LINES = byte_table([0x0A], lower=False)


def word_hashes(low: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of words; words of digits only are alike."""
    h = hash_words(low, starts, ends)
    if len(h):
        digit = np.concatenate([[0], np.cumsum((low >= 48) & (low < 58))])
        h = np.where(digit[ends] - digit[starts] == ends - starts, np.uint64(1), h)
    return h


def gram_hash(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of every n consecutive words."""
    m = len(h) - n + 1
    g = np.zeros(max(m, 0), np.uint64)
    for j in range(n if m > 0 else 0):
        g = mix(g + h[j : j + m])
    return g


def paragraph_grams(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(paragraph starts, ends, text of each, paragraph of each n-gram, n-gram hash); words of digits only are alike."""
    _, a, b, bound = words(raw, off, _LINES)
    owner = np.repeat(np.arange(len(off) - 1), np.diff(bound))
    low, starts, ends, _ = words(raw, off, _WORDS)
    h = word_hashes(low, starts, ends)
    at = np.searchsorted(a, starts, "right") - 1
    who, out = [at], [h]
    for n in GRAMS[1:]:
        m = len(h) - n + 1
        if m > 0:
            g = gram_hash(h, n)
            same = at[:m] == at[n - 1 :]
            who.append(at[:m][same])
            out.append(g[same])
    return a, b, owner, np.concatenate(who), np.concatenate(out)


@dataclass
class Model:
    """Weights by family and bucket, their calibration, each family's template n-grams, flags of the hashes of two-word grams,
    and where these grams stand: (gram, template, place), sorted, and how many words each template has."""

    families: list[str]
    weight: np.ndarray
    bias: np.ndarray
    calibration: list[tuple[float, float]]
    templates: list[list[np.ndarray]]
    flags: np.ndarray
    places: tuple[np.ndarray, np.ndarray, np.ndarray]
    lengths: np.ndarray

    def windows(self, hit: np.ndarray, gram: np.ndarray, first: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(first word, end) of the windows that template grams at words ``hit`` propose; first and end are those of the hit's text."""
        known, template, place = self.places
        a = np.searchsorted(known, gram, "left")
        n = np.searchsorted(known, gram, "right") - a
        at = ragged(a, n)
        t, start = template[at], np.repeat(hit, n) - place[at]
        order = np.lexsort((start, t))
        t, start, first, end = t[order], start[order], np.repeat(first, n)[order], np.repeat(end, n)[order]
        out = []
        for slack in (0, SLACK):
            # grams that agree on where the template starts, exactly or nearly
            new = np.flatnonzero((np.diff(t, prepend=-1) != 0) | (np.diff(start, prepend=-(1 << 40)) > slack) | (np.diff(first, prepend=-1) != 0))
            last = np.append(new[1:], len(t)) - 1
            good = last - new + 1 >= np.maximum(1, PROPOSE * (self.lengths[t[new]] - 1)) if len(t) else np.zeros(0, bool)
            new, last = new[good], last[good]
            out.append(np.stack([np.maximum(start[new], first[new]), np.minimum(start[last] + self.lengths[t[last]], end[last])], axis=1))
        both = np.unique(np.concatenate(out), axis=0)
        return both[:, 0], both[:, 1]

    def accept(self, who: np.ndarray, gram: np.ndarray) -> list[tuple[int, str, float, float]]:
        """(which, family, probability, likeness) of the n-gram sets that are a licence notice."""
        if not len(who):
            return []
        bucket = (gram >> np.uint64(64 - BITS)).astype(np.int64)
        near, place = np.unique(who, return_inverse=True)
        key = np.unique(place << BITS | bucket)
        logit = np.tile(self.bias, (len(near), 1))
        np.add.at(logit, key >> BITS, self.weight[key & ((1 << BITS) - 1)])
        logit = np.stack([s * logit[:, k] + t for k, (s, t) in enumerate(self.calibration)], axis=1)
        prob = 1 / (1 + np.exp(-np.clip(logit, -40, 40)))
        best = prob.argmax(1)
        out = []
        for i in np.flatnonzero(prob.max(1) >= BAR).tolist():
            own = np.unique(gram[place == i])
            like = max(np.isin(t, own).mean() for t in self.templates[best[i]])
            if like >= LIKENESS:
                out.append((int(near[i]), self.families[best[i]], float(prob[i, best[i]]), float(like)))
        return out

    def judge(self, raw: np.ndarray, off: np.ndarray):
        """(text, start, end, family, probability, likeness) of the licence notices, in order."""
        low, starts, ends, bound = words(raw, off, _WORDS)
        h = word_hashes(low, starts, ends)
        if len(h) < 2:
            return []
        grams = {n: gram_hash(h, n) for n in GRAMS[1:]}
        at = np.flatnonzero(self.flags[grams[2] >> np.uint64(44)])
        if not len(at):
            return []
        text = np.searchsorted(bound, at, "right") - 1
        inside = at + 1 < bound[text + 1]
        first, end = self.windows(at[inside], grams[2][at[inside]], bound[text[inside]], bound[text[inside] + 1])
        # a version at the end may have more parts than the template's
        limit = bound[np.searchsorted(bound, first, "right")]
        for _ in range(2):
            following = np.minimum(end, len(h) - 1)
            end = end + ((end < limit) & (h[following] == 1) & (starts[following] == ends[end - 1] + 1) & (raw[np.minimum(ends[end - 1], len(raw) - 1)] == 46))
        # no window goes on after an empty line
        lines = np.flatnonzero(raw == 10)
        pair = lines[np.flatnonzero(np.diff(lines) == 1)]
        whole = np.searchsorted(pair, starts[first]) == np.searchsorted(pair, ends[end - 1])
        first, end = first[whole], end[whole]
        who, found = [], []
        for n in GRAMS:
            many = np.maximum(end - first - n + 1, 0)
            who.append(np.repeat(np.arange(len(first)), many))
            found.append((h if n == 1 else grams[n])[ragged(first, many)])
        got = self.accept(np.concatenate(who), np.concatenate(found))
        bounds = np.unique(np.concatenate([lines + 1, off]))
        out, taken = [], np.zeros(len(raw) + 1, bool)
        for w, family, p, like in sorted(got, key=lambda x: (-x[3], end[x[0]] - first[x[0]], -x[2], x[0])):
            i, j = int(first[w]), int(end[w])
            a, b = int(starts[i]), int(ends[j - 1])
            if taken[a:b].any():
                continue
            taken[a:b] = True
            # what is left of a line without further words belongs to the notice
            k = int(np.searchsorted(off, a, "right")) - 1
            head = int(bounds[np.searchsorted(bounds, a, "right") - 1])
            tail = int(bounds[np.searchsorted(bounds, b - 1, "right")])
            if i == bound[k] or ends[i - 1] <= head:
                a = head
            if j == bound[k + 1] or starts[j] >= tail:
                b = tail - (1 if raw[tail - 1] == 10 else 0)
            out.append((k, a, b, family, p, like))
        # paragraphs around the hits, as texts of their own: notices that are worded too freely for a window
        line = np.unique(np.searchsorted(bounds, starts[at], "right") - 1)
        at, to = bounds[line], np.append(bounds, len(raw))[line + 1]
        text_of = np.searchsorted(off, at, "right") - 1
        part, part_off = raw[ragged(at, to - at)], np.concatenate([[0], np.cumsum(to - at)])
        a, b, owner, who, gram = paragraph_grams(part, part_off)
        shift = (at - part_off[:-1])[owner]
        a, b, owner = a + shift, b + shift, text_of[owner]
        out += [(int(owner[i]), int(a[i]), int(b[i]), *rest) for i, *rest in self.accept(who, gram) if not taken[a[i] : b[i]].any()]
        return sorted(out)


def _rows(texts: list[str]) -> tuple[np.ndarray, list[np.ndarray]]:
    """Presence matrix and n-gram sets of paragraphs."""
    data = [t.replace("\n", " ").encode() for t in texts]
    off = np.concatenate([[0], np.cumsum([len(d) for d in data])])
    _, _, owner, who, gram = paragraph_grams(np.frombuffer(b"".join(data), np.uint8), off)
    x = np.zeros((len(texts), 1 << BITS), np.float32)
    row = owner[who]
    x[row, (gram >> np.uint64(64 - BITS)).astype(np.int64)] = 1
    return x, [np.unique(gram[row == k]) for k in range(len(texts))]


def train(docs: DataFrame) -> Model:
    """Fit on written-out templates and on a bounded sample of the corpus's paragraphs.

    The unknown class has paragraphs without licence words, and near misses: paragraphs that have
    such words but are unlike every template.
    """
    rng = np.random.default_rng(3)
    sample = drawn(docs.select("doc_id", "text").where("text is not null"), MOST_TEXTS, 31, MOST_BYTES)
    lines = sample.select(F.explode(F.split("text", "\n")).alias("p")).where(F.length(F.trim("p")) > 0)
    lines = lines.withColumn("near", F.col("p").rlike(r"(?i)licen[sc]e|copyright|spdx|creative commons|all rights reserved"))
    picked = [lines.where(side).orderBy(F.xxhash64("p"), "p").limit(MOST_UNKNOWN // part).collect() for side, part in (("not near", 1), ("near", 4))]
    unknown = [r["p"] for r in picked[0]]
    known = [t for f in TEMPLATES.values() for t in _rows([re.sub(r"\{\w\}", "1", x) for x in f])[1]]
    miss = [r["p"] for r in picked[1]]
    miss = [p for p, own in zip(miss, _rows(miss)[1], strict=True) if max(np.isin(t, own).mean() for t in known) < MISS] if miss else []
    unknown = miss + unknown[: MOST_UNKNOWN - len(miss)]
    families, texts, label = list(TEMPLATES), [], []
    for k, f in enumerate(families):
        for t in TEMPLATES[f]:
            for _ in range(8):
                s = t.format(v=f"{rng.integers(1, 5)}.{rng.integers(0, 2)}", y=int(rng.integers(1990, 2030)), n=f"name{rng.integers(99)}")
                if unknown and rng.random() < 0.3:
                    s = f"{s} {unknown[rng.integers(len(unknown))][:TAIL]}"
                texts.append(s)
                label.append(k)
    filler = ["the license plate of the car", "a driving licence is needed to rent", "public domain", "general public", "version 2 of the story", "free of charge for any person"]
    texts += (unknown + filler * 10)[: MOST_UNKNOWN]
    y = np.array(label + [-1] * (len(texts) - len(label)))
    x, _ = _rows(texts)
    used = np.flatnonzero(x[y >= 0].any(axis=0))
    dense = x[:, used]
    aside = np.arange(len(y)) % 4 == 1
    weight, bias, cal = np.zeros((1 << BITS, len(families))), np.zeros(len(families)), []
    for k in range(len(families)):
        own = (y == k).astype(float)
        balance = np.where(own == 1, 1.0, np.where(y >= 0, 0.5, 0.2))
        w = fit_logistic(dense[~aside], own[~aside], balance[~aside], l2=1e-4, steps=120, rate=0.1)
        weight[used, k], bias[k] = w[:-1], w[-1]
        cal.append(calibrate(dense[aside] @ w[:-1] + w[-1], own[aside]))
    plain = [[re.sub(r"\{\w\}", "1", t) for t in TEMPLATES[f]] for f in families]
    sets = [_rows(ts)[1] for ts in plain]
    flags, known = np.zeros(1 << 20, bool), []
    for t in (t for f in plain for t in f):
        raw = np.frombuffer(t.encode(), np.uint8)
        known.append(gram_hash(word_hashes(*words(raw, np.array([0, len(raw)]), _WORDS)[:3]), 2))
        flags[known[-1] >> np.uint64(44)] = True
    lengths = np.array([len(g) + 1 for g in known])
    every = np.concatenate(known)
    order = np.argsort(every, kind="stable")
    places = (every[order], np.repeat(np.arange(len(known)), lengths - 1)[order], ragged(np.zeros(len(known), np.int64), lengths - 1)[order])
    return Model(families, weight, bias, cal, sets, flags, places, lengths)


def scan(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, families, notices) of every row of ``docs`` (doc_id, text), over its whole text.

    families: sorted distinct families found; notices: family, calibrated probability, template
    likeness and byte range of each, in order. Null and empty texts have none; repeated rows are
    scanned each; extra columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema["doc_id"].dataType.simpleString()
    item = pa.struct([("family", pa.string()), ("probability", pa.float64()), ("likeness", pa.float64()), ("start", pa.int64()), ("end", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            raw, off, _ = buffers(b.column(1))
            found: list[list[dict]] = [[] for _ in range(b.num_rows)]
            for k, s, e, f, p, like in shared.value.judge(raw, off):
                found[k].append({"family": f, "probability": p, "likeness": like, "start": s - int(off[k]), "end": e - int(off[k])})
            names = [sorted({x["family"] for x in f}) for f in found]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names, pa.list_(pa.string())), pa.array(found, pa.list_(item))], ["doc_id", "families", "notices"])

    return docs.select("doc_id", "text").mapInArrow(
        run, f"doc_id {kind}, families array<string>, notices array<struct<family: string, probability: double, likeness: double, start: bigint, end: bigint>>"
    )


def query(spark, sf_dir: str) -> DataFrame:
    """Licence families of all ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = scan(docs, train(docs))
    return found.select("doc_id", F.array_join("families", ",").alias("families"), F.size("notices").cast("long").alias("n_notices"), "notices")
