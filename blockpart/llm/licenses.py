"""License scans: sparse TF-IDF cosine to templates, then inheritance from the nearest ancestor directory.

Terms are words of ASCII letters and digits (and what stands beside them beyond ASCII, punctuation excepted), lower-cased; line ends do not part them, so
wrapped notices and comment signs do no harm. Document frequencies of the templates' terms are counted over all texts; other terms weigh as if in none.

Every window of a text, from every place, of three quarters of, as many as, or five quarters of a template's terms (or the whole of a shorter text) is
compared with the template. Two bounds save work and lose nothing: a cosine c needs shared terms that hold c squared of the template's squared norm, which is
looked up for a whole batch of texts by one matrix product; and a window's cosine is at most its exact dot product over the norm it would have if no term were
repeated, both differences of prefix sums, so windows are scored only while that can still win. The best cosine of at least THRESHOLD gives the text's own
licence (ties: the longer template, then the name that sorts first). Below THRESHOLD the score is 0.

Files named LICENSE, LICENCE, COPYING or UNLICENSE (any extension) speak for their directory. A file without a licence of its own takes that of the
nearest directory above it that has one: directories, not files, are joined with their ancestors, and files with their directory.

Results for odd input: a null or empty text has no licence of its own but inherits; a null path has no directory; repeated rows repeat; of
several licence files in a directory the best score counts, then the name that sorts first; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import ALNUM, LOWER, WordHash, byte_view, give_back, mapped, materialise, row_slices, word_spans

THRESHOLD = 0.75
#: Notices as they are commonly written: fixed values.
TEMPLATES = {
    "AGPL-3.0": ("Licensed under the GNU Affero General Public License, version 3.", "This program is licensed under the GNU Affero General Public License", "GNU AFFERO GENERAL PUBLIC LICENSE Version 3, 19 November 2007"),
    "Apache-2.0": ("Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.", "SPDX-License-Identifier: Apache-2.0", "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/"),
    "BSD-2-Clause": ("Released under the BSD 2-Clause License.", "SPDX-License-Identifier: BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    "BSD-3-Clause": ("Released under the BSD 3-Clause License.", "SPDX-License-Identifier: BSD-3-Clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    "CC0-1.0": ("Dedicated to the public domain under CC0 1.0.", "SPDX-License-Identifier: CC0-1.0", "Creative Commons CC0 1.0 Universal"),
    "GPL-2.0": ("This work is licensed under the GNU General Public License, version 2.", "SPDX-License-Identifier: GPL-2.0-only", "GNU GENERAL PUBLIC LICENSE Version 2, June 1991"),
    "GPL-3.0": ("This work is licensed under the GNU General Public License, version 3.", "SPDX-License-Identifier: GPL-3.0-or-later", "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    "ISC": ("Released under the ISC License.", "SPDX-License-Identifier: ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    "LGPL-3.0": ("This library is licensed under the GNU Lesser General Public License, version 3.", "SPDX-License-Identifier: LGPL-3.0-or-later", "GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    "MIT": ("Released under the MIT License.", "Licensed under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files", "SPDX-License-Identifier: MIT"),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", "SPDX-License-Identifier: MPL-2.0", "Mozilla Public License Version 2.0"),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
}
TERM = re.compile(r"[^\W_]+")
FILE = r"(?i)^(un)?(licen[sc]e|copying)(\.[^/]*)?$"


def terms(text: str) -> list[str]:
    return TERM.findall(text.lower())


def template_terms() -> list[str]:
    return sorted({t for notices in TEMPLATES.values() for n in notices for t in terms(n)})


class Terms:
    """Finds the terms of texts, and the number in the templates' vocabulary of each (-1: none)."""

    def __init__(self):
        self.vocabulary, self.hashes = template_terms(), WordHash()
        raw, end = np.frombuffer("".join(self.vocabulary).encode(), np.uint8), np.cumsum([len(t) for t in self.vocabulary])
        keys = self.hashes(raw, end - [len(t) for t in self.vocabulary], end)
        self.order = np.argsort(keys)
        self.keys = keys[self.order]

    def __call__(self, part: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of texts end to end in part: each term's hash and number, and per text its first term (n + 1)."""
        flag = ALNUM[part]
        if len(part) > 2:  # general punctuation: U+2000 to U+206F
            mark = np.flatnonzero((part[:-2] == 0xE2) & ((part[1:-1] == 0x80) | (part[1:-1] == 0x81)))
            for k in range(3):
                flag[mark + k] = False
        start, stop, first = word_spans(flag, at)
        own = self.hashes(LOWER[part], start, stop)
        place = np.minimum(np.searchsorted(self.keys, own), len(self.keys) - 1)
        return own, np.where(self.keys[place] == own, self.order[place], -1), first


def frequencies(files: DataFrame) -> tuple[int, dict[str, int]]:
    """The number of texts, and of texts that hold each template term."""
    vocabulary = template_terms()

    def run(batches):
        find = Terms()
        total, many = np.zeros(len(vocabulary), np.int64), 0
        for batch in batches:
            data, at = byte_view(batch.column(0))
            many += batch.num_rows
            for a, b in row_slices(at):
                _, number, first = find(data[at[a] : at[b]], at[a : b + 1] - at[a])
                doc = np.repeat(np.arange(b - a), np.diff(first))[number >= 0]
                total += np.bincount(np.unique(doc * len(vocabulary) + number[number >= 0]) % len(vocabulary), minlength=len(vocabulary))
        yield pa.RecordBatch.from_arrays([pa.array([-1, *range(len(vocabulary))]), pa.array([many, *total.tolist()])], names=["term", "n"])

    rows = dict(mapped(files.select("text"), run, "term bigint, n bigint").groupBy("term").agg(F.sum("n")).collect())
    return rows.get(-1, 0), {t: rows.get(i, 0) for i, t in enumerate(vocabulary)}


class Matcher:
    def __init__(self, n: int, known: dict[str, int], threshold: float = THRESHOLD):
        self.find, self.threshold = Terms(), threshold
        self.rare = math.log(1 + n) + 1
        self.idf = np.array([math.log((1 + n) / (1 + known[t])) + 1 for t in self.find.vocabulary])
        place = {t: i for i, t in enumerate(self.find.vocabulary)}
        rows = []
        for name, notices in TEMPLATES.items():
            for notice in notices:
                own = terms(notice)
                weight = np.bincount([place[t] for t in own], minlength=len(place)) * self.idf
                rows.append((-len(own), name, weight / math.sqrt(weight @ weight)))
        # The longest first, then by name: the first of equal scores wins.
        self.templates = sorted(rows, key=lambda r: r[:2])
        self.weights = np.array([w for _, _, w in self.templates])

    def cosine(self, hashes: np.ndarray, number: np.ndarray, weight: np.ndarray) -> float:
        """Of one window's terms with a template."""
        other = number < 0
        count = np.bincount(number[~other], minlength=len(weight)) * self.idf
        strange = np.unique(hashes[other], return_counts=True)[1] * self.rare
        size = math.sqrt(count @ count + strange @ strange)
        return float(count @ weight) / size if size else 0.0

    def window(self, hashes: np.ndarray, number: np.ndarray, n: int, weight: np.ndarray, least: float) -> float:
        """The best cosine of a window if it is over `least`, else 0."""
        known = number >= 0
        idf = np.where(known, self.idf[number], self.rare)
        dot = np.concatenate([[0.0], np.cumsum(np.where(known, self.idf[number] * weight[number], 0.0))])
        norm = np.concatenate([[0.0], np.cumsum(idf * idf)])
        best = least
        for size in sorted({min(len(number), s) for s in (n, -(-3 * n // 4), 5 * n // 4)}):
            bound = (dot[size:] - dot[:-size]) / np.sqrt(norm[size:] - norm[:-size])
            some = np.flatnonzero(bound > best + 1e-9)
            for k in some[np.argsort(-bound[some], kind="stable")].tolist():
                if bound[k] <= best + 1e-9:
                    break
                best = max(best, self.cosine(hashes[k : k + size], number[k : k + size], weight))
        return best if best > least else 0.0

    def best(self, texts: pa.Array) -> list[tuple[str | None, float]]:
        data, at = byte_view(texts)
        out: list[tuple[str | None, float]] = []
        for a, b in row_slices(at):
            hashes, number, first = self.find(data[at[a] : at[b]], at[a : b + 1] - at[a])
            doc = np.repeat(np.arange(b - a), np.diff(first))
            held = np.zeros((b - a, len(self.idf)), np.float32)
            held[doc[number >= 0], number[number >= 0]] = 1
            hopeful = held @ (self.weights * self.weights).T.astype(np.float32) >= self.threshold**2 - 1e-5
            found: dict[int, tuple[str, float]] = {}
            for d, t in zip(*(x.tolist() for x in np.nonzero(hopeful)), strict=True):
                size, name, weight = self.templates[t]
                own = slice(first[d], first[d + 1])
                score = self.window(hashes[own], number[own], -size, weight, max(self.threshold - 1e-9, found.get(d, ("", 0.0))[1]))
                if score:
                    found[d] = name, score
            out += [(found[d][0], round(found[d][1], 9)) if d in found else (None, 0.0) for d in range(b - a)]
        return out


def own_licenses(files: DataFrame) -> DataFrame:
    """The rows and columns of files(path, text, ...), without text, with own (a licence or null) and score."""
    n, known = frequencies(files)
    rest = [f for f in files.schema if f.name != "text"]

    def run(batches):
        matcher = Matcher(n, known)
        for batch in batches:
            found = matcher.best(batch.column(0))
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names=[*batch.schema.names[1:], "own", "score"])
        give_back()

    return mapped(files.select("text", *[F.col(f"`{f.name}`") for f in rest]), run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rest), "own string, score double"]))


def inherited(found: DataFrame) -> DataFrame:
    """Adds directory, license (own, or that of the nearest directory above) and license_from (the file or directory that gives it)."""
    folder = F.regexp_extract("path", r"^(.*)/[^/]*$", 1)
    found = found.withColumn("directory", F.when(F.col("path").isNotNull(), folder))
    speaks = F.regexp_extract("path", r"([^/]*)$", 1).rlike(FILE) & F.col("own").isNotNull()
    by_directory = found.where(speaks).groupBy("directory").agg(F.min_by("own", F.struct(-F.col("score"), F.col("own"))).alias("given"))
    steps = F.split("directory", "/")
    above = F.transform(F.sequence(F.lit(0), F.size(steps)), lambda k: F.array_join(F.slice(steps, 1, k), "/"))
    chains = found.where(F.col("directory").isNotNull()).select("directory").distinct().select("directory", F.explode(F.array_distinct(above)).alias("above"))
    nearest = chains.join(by_directory.select(F.col("directory").alias("above"), "given"), "above").groupBy("directory").agg(F.max_by(F.struct("above", "given"), F.length("above")).alias("near"))
    return found.join(nearest, "directory", "left").withColumn("license", F.coalesce("own", F.col("near.given"))).withColumn("license_from", F.when(F.col("own").isNotNull(), F.col("path")).when(F.col("near").isNotNull(), F.col("near.above"))).drop("near")


def as_files(docs: DataFrame) -> DataFrame:
    """documents as a tree of files: source / blocks of 512 ids / of 32 ids / id, where the first of a block is its licence file. doc_id, path, text."""
    i = F.col("doc_id")
    block = lambda n: F.floor(i / n).cast("string")
    where = F.when(i % 512 == 0, F.concat_ws("/", F.col("source"), block(512), F.lit("LICENSE"))).when(i % 32 == 0, F.concat_ws("/", F.col("source"), block(512), block(32), F.lit("LICENSE"))).otherwise(F.concat_ws("/", F.col("source"), block(512), block(32), F.concat(i.cast("string"), F.lit(".txt"))))
    return docs.select("doc_id", F.when(i.isNotNull(), where).alias("path"), "text")


def report(docs: DataFrame) -> DataFrame:
    """doc_id, path, own, score, license, license_from of every document."""
    return inherited(materialise(own_licenses(as_files(docs)))).select("doc_id", "path", F.col("own").alias("own_license"), "score", "license", "license_from")
