"""Licence scan: sparse TF-IDF cosine to notice templates, then inheritance along directories.

Every line of every whole text, every block of two to four successive lines that
hold words (headers and wrapped notices) and the text as a whole are compared with
the templates over their vocabulary (words and word pairs); document frequencies
are those of the corpus. A term weighs its count in the unit times its inverse
document frequency. Terms outside the templates count in a unit's norm as often as
they occur, each with the mean square weight of an occurrence of the unit's own
template terms, so that neither the size of the table nor a notice that stands in
most files changes what is found. A file without a notice of its own inherits from the nearest
ancestor directory that holds a licence file: the ancestors of each distinct
directory are joined with the licensed directories, and files join their directory.

Defined cases: null and empty texts have no notice; equal cosines go to the
template that is first by name; several licence files of one directory count by
best score, then name; a null path has no directory and inherits nothing; repeated
rows are reported each; further columns are ignored; an empty table gives none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.scratch import materialise, small_side
from .kernel import ALNUM, Lookup, Words, blocks, shingles
from .rows import with_text_columns

#: Short notices by licence.
TEMPLATES = {
    "Apache-2.0": ("Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0; you may not use this file except in compliance with the License."),
    "BSD-3-Clause": ("Redistribution and use in source and binary forms, with or without modification, are permitted.", "Released under the BSD 3-Clause License."),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "GPL-2.0": ("This work is licensed under the GNU General Public License, version 2.",),
    "GPL-3.0": ("This work is licensed under the GNU General Public License, version 3.",),
    "MIT": ("Released under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software."),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
}
THRESHOLD = 0.7
#: Blocks of up to this many lines are units of their own.
BLOCK_LINES = 4


def _terms(words: Words) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words and pairs, and the word position of each."""
    pair, fits = shingles(words, 2)
    n = np.arange(len(words.hash))
    return np.concatenate([words.hash, pair[fits]]), np.concatenate([n, n[fits]])


class Templates:
    def __init__(self, templates: dict[str, tuple[str, ...]] = TEMPLATES):
        self.names, found = [], []
        for name in sorted(templates):
            for text in templates[name]:
                raw = np.frombuffer(text.encode(), np.uint8)
                self.names.append(name)
                found.append(np.unique(_terms(Words(raw, np.array([0, len(raw)]), ALNUM))[0], return_counts=True))
        self.terms = np.unique(np.concatenate([t for t, _ in found])) if found else np.zeros(0, np.uint64)
        self.count = np.zeros((len(self.terms), len(found)))
        for k, (t, n) in enumerate(found):
            self.count[np.searchsorted(self.terms, t), k] = n

    def weigh(self, frequency: np.ndarray, rows: int) -> None:
        self.idf = np.log((1 + rows) / (1 + frequency)) + 1e-3
        weights = self.count * self.idf[:, None]
        self.weights = weights / np.maximum(np.sqrt((weights**2).sum(0)), 1e-12)


def term_frequency(docs: DataFrame, text_col: str, templates: Templates) -> tuple[np.ndarray, int]:
    """In how many documents each template term occurs, and the number of documents."""
    held = docs.sparkSession.sparkContext.broadcast(templates.terms)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, seen = Lookup(held.value), np.zeros(len(held.value) + 1, np.int64)
        for rows, data, offsets in blocks(batches, text_col):
            words = Words(data, offsets, ALNUM)
            term, place = _terms(words)
            at, known = table.find(term)
            owner = np.searchsorted(words.bounds, place[known], "right") - 1
            seen[:-1] += np.bincount(np.unique(owner * len(table.keys) + at[known]) % len(table.keys), minlength=len(table.keys)) if known.any() else 0
            seen[-1] += rows.num_rows
        yield pa.record_batch({"at": pa.array(np.arange(len(seen), dtype=np.int32)), "n": pa.array(seen)})

    got = docs.select(text_col).mapInArrow(count, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(len(templates.terms) + 1, np.int64)
    out[got.column("at").to_numpy()] = got.column("n").to_numpy()
    return out[:-1], int(out[-1])


def _cosines(unit: np.ndarray, at: np.ndarray, words: np.ndarray, t: Templates) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Units that hold template terms (``at``, any order) with their best template and its cosine; ``words``: a unit's length."""
    (key, n), terms = np.unique(unit * len(t.terms) + at, return_counts=True), len(t.terms)
    owner, at = key // terms, key % terms
    names, starts = np.unique(owner, return_index=True)
    own = np.add.reduceat(n, starts)
    square = np.add.reduceat((n * t.idf[at]) ** 2, starts)
    mean = np.add.reduceat(n * t.idf[at] ** 2, starts) / own
    # Of w words in a row there are w words and w - 1 pairs.
    outside = 2 * words[names] - 1 - own
    dots = np.add.reduceat((n * t.idf[at])[:, None] * t.weights[at], starts, axis=0)
    cos = dots / np.sqrt(square + outside * mean)[:, None]
    best = np.round(cos, 12).argmax(1)
    return names, best, cos[np.arange(len(names)), best]


def _units(words: Words, breaks: np.ndarray, place: np.ndarray, last: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Blocks of 1 to BLOCK_LINES lines, then whole texts: (unit, index of a term in it, words a unit, text of a unit).

    Terms go from word ``place`` to word ``last``. Lines without words do not count.
    """
    text = np.repeat(np.arange(len(words.bounds) - 1), np.diff(words.bounds))
    raw = np.searchsorted(breaks, words.start) + text  # breaks of texts count as breaks of lines
    fresh = np.append(True, raw[1:] != raw[:-1])
    line, begin = np.cumsum(fresh) - 1, np.flatnonzero(fresh)
    owner = text[begin]
    for lines in range(1, BLOCK_LINES + 1):
        units, terms = [], []
        for back in range(lines):
            unit = line[place] - back
            fits = np.flatnonzero((unit >= 0) & (owner[np.maximum(unit, 0)] == text[place]) & (line[last] - unit < lines))
            units.append(unit[fits])
            terms.append(fits)
        stop = np.minimum(np.append(begin, len(text))[np.minimum(np.arange(len(begin)) + lines, len(begin))], words.bounds[owner + 1])
        yield np.concatenate(units), np.concatenate(terms), stop - begin, owner
    yield text[place], np.arange(len(place)), np.diff(words.bounds), np.arange(len(words.bounds) - 1)


def detect(docs: DataFrame, text_col: str = "text", templates: dict[str, tuple[str, ...]] = TEMPLATES, threshold: float = THRESHOLD, keep: list[str] | None = None) -> DataFrame:
    """``keep`` (default: all) columns with ``own_license`` and ``own_score`` (best cosine of a line or of the whole text)."""
    t = Templates(templates)
    t.weigh(*term_frequency(docs, text_col, t))
    held = docs.sparkSession.sparkContext.broadcast(t)

    def make():
        t = held.value
        table = Lookup(t.terms)

        def run(data: np.ndarray, offsets: np.ndarray) -> dict:
            words = Words(data, offsets, ALNUM)
            term, place = _terms(words)
            at, known = table.find(term)
            score, best = np.zeros(len(offsets) - 1), np.full(len(offsets) - 1, -1)
            on = np.flatnonzero(known)
            last = place[on] + (on >= len(words.hash))
            found = []
            for unit, which, length, owner in _units(words, np.flatnonzero(data == 10), place[on], last) if len(on) else ():
                if len(unit):
                    names, template, cos = _cosines(unit, at[on[which]], length, t)
                    found.append((owner[names], template, cos))
            if found:
                owner, template, cos = (np.concatenate(x) for x in zip(*found, strict=True))
                order = np.lexsort((template, -np.round(cos, 12), owner))
                texts, first = np.unique(owner[order], return_index=True)
                score[texts], best[texts] = cos[order[first]], template[order[first]]
            ok = score >= threshold
            return {"own_license": pa.array([t.names[b] if k else None for b, k in zip(best, ok, strict=True)], pa.string()), "own_score": score}

        return run

    return with_text_columns(docs, text_col, make, {"own_license": T.StringType(), "own_score": T.DoubleType()}, keep)


def _parent(path):
    return F.regexp_extract(path, r"^(.*)/[^/]*$", 1)


def inherit(files: DataFrame, path_col: str = "path", license_name: str = r"(?i)(^|/)(licen[cs]e|copying)[^/]*$") -> DataFrame:
    """Adds ``license`` and ``inherited_from`` (a directory, null for a file's own notice) to rows of ``detect``."""
    rows = files.withColumn("_dir", _parent(F.col(path_col)))
    holders = rows.where(F.col(path_col).rlike(license_name) & F.col("own_license").isNotNull())
    licensed = materialise(holders.groupBy(F.col("_dir").alias("ancestor")).agg(F.min_by("own_license", F.struct(-F.col("own_score"), "own_license")).alias("found")), "licensed-dirs")
    dirs = rows.select("_dir").where(F.col("_dir").isNotNull()).distinct()
    parts = F.split("_dir", "/")
    ancestors = F.transform(F.sequence(F.size(parts), F.lit(1), F.lit(-1)), lambda k: F.array_join(F.slice(parts, F.lit(1), k), "/"))
    steps = dirs.select("_dir", F.explode(ancestors).alias("ancestor"))
    nearest = steps.join(small_side(licensed, 100_000), "ancestor").groupBy("_dir").agg(F.max_by(F.struct("found", "ancestor"), F.length("ancestor")).alias("_near"))
    joined = rows.join(small_side(materialise(nearest, "nearest"), 100_000), "_dir", "left")
    own = F.col("own_license").isNotNull()
    return joined.select(*files.columns, F.coalesce("own_license", F.col("_near.found")).alias("license"), F.when(~own, F.col("_near.ancestor")).alias("inherited_from"))
