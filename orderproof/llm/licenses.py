"""Licence scan by a trained paragraph classifier.

Paragraphs, runs of lines with words, are scored by multinomial logistic regression over sparse word n-grams of licence texts. It
is trained on labelled samples made from templates of each family, whole and with words dropped, against all ordinary lines of the
documents as the unknown class. The threshold of the unknown class is calibrated on samples that didn't train, and a
family is told only where its template confirms it: enough of the template's word bigrams stand close together in the paragraph,
whatever its line breaks. Of notices that share words the one nearer to its template is told.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm.common import mix64, text_slices, word_hashes, words_of
from orderproof.sources.scratch import scope, written

UNKNOWN = "unknown"
#: Notices by which texts name their licence, by family.
TEMPLATES = {
    "MIT": ["Released under the MIT License.", "Licensed under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"],
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."],
    "GPL": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License"],
    "LGPL": ["This library is licensed under the GNU Lesser General Public License, version 2.1.", "you can redistribute it under the terms of the GNU Lesser General Public License"],
    "BSD": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", "Use of this source code is governed by a BSD-style license.", "Released under the BSD 3-Clause License."],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", "Licensed under the Mozilla Public License 2.0."],
    "CC0": ["To the extent possible under law, the author has waived all copyright and related rights under CC0.", "Dedicated to the public domain under CC0 1.0 Universal.", "Licensed under CC0 1.0."],
    "AGPL": ["This work is licensed under the GNU Affero General Public License, version 3.", "you can redistribute it under the terms of the GNU Affero General Public License"],
    "ISC": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted", "Released under the ISC License.", "Licensed under the ISC License."],
    "EPL-2.0": ["This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0", "Licensed under the Eclipse Public License 2.0."],
    "Unlicense": ["This is free and unencumbered software released into the public domain.", "Released under the Unlicense."],
    "BSL-1.0": ["Distributed under the Boost Software License, Version 1.0.", "Licensed under the Boost Software License 1.0."],
    "Zlib": ["This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.", "Released under the zlib License."],
} | {
    f"CC-{short}": [
        f"This work is licensed under a Creative Commons {long} 4.0 International License.", f"Available under the Creative Commons {long} license.",
        f"Licensed under CC {short} 4.0.", f"Licensed under CC-{short}-4.0.", f"This work is available under a CC {short} license.",
    ]
    for short, long in (
        ("BY", "Attribution"), ("BY-NC", "Attribution-NonCommercial"), ("BY-SA", "Attribution-ShareAlike"), ("BY-ND", "Attribution-NoDerivatives"),
        ("BY-NC-SA", "Attribution-NonCommercial-ShareAlike"), ("BY-NC-ND", "Attribution-NonCommercial-NoDerivatives"),
    )
}
FAMILIES = [UNKNOWN, *TEMPLATES]
BITS = 18
STRIP = ".,;:!?\"'()<>[]"


def tokens(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row) of the words of texts, lower case, without punctuation at either end; marks as of comments are no words."""
    words, row = words_of(text)
    if not len(words):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    d = words.dictionary_encode()
    plain = [w.strip(STRIP) for w in d.dictionary.to_pylist()]
    at, real = d.indices.to_numpy(), np.array([any(c.isalnum() for c in w) for w in plain])
    return word_hashes(pa.array(plain, pa.large_string()))[at][real[at]], row[real[at]]


def _cut(x: np.ndarray) -> np.ndarray:
    return (mix64(x) >> np.uint64(64 - BITS)).astype(np.int64)


def _twos(h: np.ndarray) -> np.ndarray:
    return mix64(mix64(h[:-1]) * np.uint64(0x9E3779B97F4A7C15) + h[1:])


def grams(text: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, feature, width) of the word unigrams and bigrams of texts."""
    h, row = tokens(text)
    inside = row[:-1] == row[1:]
    return np.concatenate([row, row[:-1][inside]]), np.concatenate([_cut(h), _cut(_twos(h)[inside])]), np.concatenate([np.ones(len(row), np.int64), np.full(inside.sum(), 2)])


@dataclass
class LicenceModel:
    column: np.ndarray  # of each feature, or -1
    weights: np.ndarray  # (columns, families)
    bias: np.ndarray
    threshold: float
    templates: list[tuple[int, np.ndarray]]  # family and the sorted bigrams of each of its texts
    confirm: float = 0.6

    def probabilities(self, features: np.ndarray) -> np.ndarray:
        z = self.bias + self.weights[np.unique(self.column[features[self.column[features] >= 0]])].sum(0)
        p = np.exp(z - z.max())
        return p / p.sum()

    def told(self, lines: pa.Array, owner: np.ndarray) -> list[tuple[int, int, float, float]]:
        """(line, family, probability, share of the template) of the notices in lines, of which owner names the text; line is
        where the notice begins. A notice may go over the lines of a paragraph, and a paragraph may hold several."""
        h, row = tokens(lines)
        if len(h) < 2:
            return []
        near = (np.diff(row) <= 1) & (owner[row[:-1]] == owner[row[1:]])  # a line without words ends the paragraph
        para = np.concatenate([[0], np.cumsum(~near)])
        one, two = _cut(h), np.where(near, _cut(_twos(h)), -1)
        out, found = [], {}
        for t, (_, want) in enumerate(self.templates):
            at = np.flatnonzero(np.isin(two, want))
            if not len(at):
                continue
            # paragraphs without enough different bigrams of the template can't confirm it
            have = np.unique(np.stack([para[at], two[at]]), axis=1)[0]
            ids, n = np.unique(have, return_counts=True)
            at = at[np.isin(para[at], ids[n >= self.confirm * len(want)])]
            for p in np.split(at, np.flatnonzero(np.diff(para[at])) + 1) if len(at) else []:
                found.setdefault(int(para[p[0]]), []).append((t, p))
        for places in found.values():
            windows = []
            for t, p in places:
                k, want = self.templates[t]
                for i, first in enumerate(p.tolist()):
                    seen, last = set(), first
                    for x in p[i:].tolist():
                        if x >= first + 2 * len(want) + 4:
                            break
                        if int(two[x]) not in seen:
                            seen.add(int(two[x]))
                            last = x
                    share = len(seen) / len(want)
                    if share >= self.confirm:
                        windows.append((len(seen) / (len(want) + last + 1 - first - len(seen)), share, k, first, last + 1))
            scored = []
            for close, share, k, first, last in windows:
                prob = self.probabilities(np.concatenate([one[first : last + 1], two[first:last]]))
                if 1 - prob[0] >= self.threshold:
                    scored.append((-close, -float(prob[k]), first, last, k, share))
            taken: list[tuple[int, int]] = []
            for _, prob, first, last, k, share in sorted(scored):
                if all(last < a or b < first for a, b in taken):
                    taken.append((first, last))
                    out.append((int(row[first]), k, -prob, share))
        return sorted(out)


def _samples(rng, each: int) -> tuple[list[str], list[int]]:
    texts, labels = [], []
    for k, family in enumerate(FAMILIES[1:], 1):
        for _ in range(each):
            w = TEMPLATES[family][rng.integers(len(TEMPLATES[family]))].split()
            drop = rng.random(len(w)) < 0.1 * rng.integers(0, 2)
            w = [x for x, d in zip(w, drop, strict=True) if not d] or w
            texts.append(" ".join(w))
            labels.append(k)
    return texts, labels


def _sets(docs: DataFrame, column: np.ndarray, text_col: str) -> DataFrame:
    """(cols, n, held): the different sets of template columns of all ordinary lines of docs (16-bit numbers in order), how many lines have
    each, and whether it calibrates. Ordinary are lines with words that don't hold "licen"."""

    def run(batches):
        for batch in batches:
            for part in text_slices(batch):
                lines = pc.list_flatten(pc.split_pattern(pc.fill_null(part.column("text"), "").cast(pa.large_string()), "\n"))
                lines = lines.filter(pc.and_(pc.greater(pc.utf8_length(pc.utf8_trim_whitespace(lines)), 0), pc.invert(pc.match_substring(lines, "licen", ignore_case=True))))
                row, feature, _ = grams(lines)
                hit = column[feature] >= 0
                pair = np.unique(row[hit] * len(column) + column[feature[hit]])
                row, col = pair // len(column), (pair % len(column)).astype("<u2").tobytes()
                cuts = [0, *(np.flatnonzero(np.diff(row)) + 1).tolist(), len(row)] if len(row) else [0]
                found = Counter(col[2 * i : 2 * j] for i, j in pairwise(cuts))
                found[b""] = len(lines) - sum(found.values())
                yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.binary()), pa.array(list(found.values()), pa.int64())], ["cols", "n"])

    counted = docs.select(F.col(text_col).alias("text")).mapInArrow(run, "cols binary, n long").groupBy("cols").agg(F.sum("n").alias("n"))
    return counted.filter("n > 0").withColumn("held", F.pmod(F.xxhash64("cols"), F.lit(4)) == 3)


def _pass(col: np.ndarray, size: np.ndarray, y: np.ndarray, n: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, float, np.ndarray]:
    """(gradient, loss, probabilities) of rows with labels y, weights n and `size` columns each, which stand in col one row after the other;
    the last row of w is the bias."""
    z, full = np.tile(w[-1], (len(size), 1)), size > 0
    if len(col):
        z[full] += np.add.reduceat(w[col], (np.cumsum(size) - size)[full])
    z -= z.max(1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(1, keepdims=True)
    at = np.arange(len(y))
    loss = -float((n * np.log(np.maximum(p[at, y], 1e-300))).sum())
    g = p * n[:, None]
    g[at, y] -= n
    each = np.repeat(g, size, axis=0)
    return np.vstack([np.stack([np.bincount(col, each[:, k], len(w) - 1) for k in range(w.shape[1])], 1), g.sum(0)]), loss, p


def _over(sets: DataFrame, w: np.ndarray, held: bool) -> tuple[np.ndarray, float, float]:
    """(gradient, loss, greatest probability of any family) over the ordinary sets that calibrate, or that train."""

    def run(batches):
        total, loss, most = np.zeros_like(w), 0.0, 0.0
        for batch in batches:
            cols = batch.column("cols").to_pylist()
            if cols:
                size = np.array([len(x) // 2 for x in cols])
                g, more, p = _pass(np.frombuffer(b"".join(cols), "<u2").astype(np.int64), size, np.zeros(len(cols), np.int64), batch.column("n").to_numpy().astype(float), w)
                total, loss, most = total + g, loss + more, max(most, float(1 - p[:, 0].min()))
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary()), pa.array([loss]), pa.array([most])], ["g", "loss", "most"])

    rows = sets.filter(F.col("held") == held).select("cols", "n").mapInArrow(run, "g binary, loss double, most double").collect()
    return sum((np.frombuffer(r.g).reshape(w.shape) for r in rows), np.zeros_like(w)), sum(r.loss for r in rows), max((r.most for r in rows), default=0.0)


def fit(docs: DataFrame, each: int = 60, steps: int = 60, ordinary: float = 0.75, seed: int = 5, text_col: str = "text") -> LicenceModel:
    """Trains on `each` samples of every family and all ordinary lines of docs as unknown, which together weigh `ordinary` of the whole and
    one as much as another; every fourth sample, and of ordinary lines every fourth set of template words, calibrates instead.

    Lines count only by the template words and bigrams they hold, so their different sets are counted once and each step sums its
    gradient over all of them in Spark: the driver holds the weights, not the lines. Steps are accelerated ones, begun anew with half
    the rate where the loss grew.
    """
    rng = np.random.default_rng(seed)
    texts, labels = _samples(rng, each)
    label = np.array(labels)
    base = [(k, t) for k, f in enumerate(FAMILIES[1:], 1) for t in TEMPLATES[f]]
    _, feature, _ = grams(pa.array([t for _, t in base], pa.large_string()))
    column = np.full(1 << BITS, -1)
    column[np.unique(feature)] = np.arange(len(np.unique(feature)))
    templates = []
    for k, t in base:
        _, f, w = grams(pa.array([t], pa.large_string()))
        templates.append((k, np.unique(f[w == 2])))
    train = np.arange(len(texts)) % 4 != 3
    row, feature, _ = grams(pa.array([t for t, own in zip(texts, train, strict=True) if own], pa.large_string()))
    hit = column[feature] >= 0
    n, m = int(train.sum()), int(column.max()) + 1
    x = np.unique(row[hit] * m + column[feature[hit]])
    own = x % m, np.bincount(x // m, minlength=n), label[train], np.full(n, (1 - ordinary) / n)
    with scope(docs.sparkSession):
        sets = written(_sets(docs, column, text_col))
        lines = sets.filter("NOT held").agg(F.sum("n")).head()[0] or 1
        w = ahead = np.zeros((m + 1, len(FAMILIES)))
        rate, k, best = 4.0, 0, np.inf
        ridge = np.full((m + 1, 1), 1e-4)
        ridge[-1] = 0  # of the bias
        for _ in range(steps):
            g, loss, _ = _pass(*own, ahead)
            more, other, _ = _over(sets, ahead, False)
            loss += other * ordinary / lines + 0.5 * float((ridge * ahead**2).sum())
            if loss > best + 1e-9:
                rate, k, ahead, best = rate / 2, 0, w, np.inf
                continue
            k, best = k + 1, loss
            now = ahead - rate * (g + more * (ordinary / lines) + ridge * ahead)
            w, ahead = now, now + (k - 1) / (k + 2) * (now - w)
        # the unknown class: the least threshold, 0.5 or more, that no calibrating ordinary line reaches
        most = _over(sets, w, True)[2]
    return LicenceModel(column, w[:-1], w[-1], float(min(0.95, max(0.5, most * 1.05))), templates)


def scan(docs: DataFrame, model: LicenceModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, line, family, probability, share) for every notice of a licence in docs, line from 0 being where it begins.

    Null and empty texts give nothing. Repeated and null ids are rows of their own; other columns aren't read.
    """

    def run(batches):
        for batch in batches:
            out = [[], [], [], [], []]
            for part in text_slices(batch):
                lists = pc.split_pattern(pc.fill_null(part.column("text"), "").cast(pa.large_string()), "\n")
                count = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
                owner = np.repeat(np.arange(len(count)), count)
                first = np.concatenate([[0], np.cumsum(count)[:-1]])
                ids = part.column("id").to_pylist()
                for r, k, p, share in model.told(lists.flatten(), owner):
                    for col, v in zip(out, (ids[owner[r]], int(r - first[owner[r]]), FAMILIES[k], p, share), strict=True):
                        col.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.string()), pa.array(out[3], pa.float64()), pa.array(out[4], pa.float64())], ["id", "line", "family", "probability", "share"])

    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return texts.mapInArrow(run, "id long, line int, family string, probability double, share double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The licences named in documents, a row a notice."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return scan(docs, fit(docs)).withColumnRenamed("id", "doc_id")
