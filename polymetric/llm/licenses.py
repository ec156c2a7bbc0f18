"""Licence scans: sparse TF-IDF cosine of notices to licence templates, then inheritance from the nearest ancestor
directory that has a licence file, by joins on paths. Files named as licence files are also compared as wholes, and in windows at
quarter steps, with the texts of short licences and the openings of long ones.

Terms are weighed by their document frequency over the whole table. A unit is a line with an anchor term, a run of such
lines, or a window of a template's length, over line ends too, that holds an anchor of the template. Terms outside the
templates are counted if they stand in a unit that passes with the least weight they can have. Anchors are chosen so that a unit without any stays below the
threshold with every template (the terms left over can't make up that much of a template's norm), so skipping the
other lines loses nothing.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, heavy_join

WORD = re.compile(r"\w+")
#: Short notices in which licences are commonly granted.
TEMPLATES = {
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
        "SPDX-License-Identifier: Apache-2.0",
    ],
    "MIT": [
        "Released under the MIT License",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction",
        "SPDX-License-Identifier: MIT",
    ],
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version",
        "SPDX-License-Identifier: GPL-3.0-or-later",
    ],
    "BSD-3-Clause": [
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
        "SPDX-License-Identifier: BSD-3-Clause",
    ],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "SPDX-License-Identifier: MPL-2.0"],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License"],
    "CC-BY-4.0": ["Licensed under CC BY 4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"],
}
_WARRANTY = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_BSD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
#: The texts of short licences, and how the files of long ones open.
FILE_TEMPLATES = {
    "MIT": [
        """MIT License Copyright (c) year holder Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    ],
    "ISC": [
        """ISC License Copyright (c) year holder Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    ],
    "BSD-2-Clause": [f"BSD 2-Clause License Copyright (c) year, holder All rights reserved. {_BSD} {_WARRANTY}"],
    "BSD-3-Clause": [
        f"BSD 3-Clause License Copyright (c) year, holder All rights reserved. {_BSD} 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. {_WARRANTY}"
    ],
    "Unlicense": [
        """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors."""
    ],
    "Apache-2.0": [
        """Apache License Version 2.0, January 2004 http://www.apache.org/licenses/ TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION 1. Definitions. "License" shall mean the terms and conditions for use, reproduction, and distribution as defined by Sections 1 through 9 of this document. "Licensor" shall mean the copyright owner or entity authorized by the copyright owner that is granting the License."""
    ],
    "GPL-3.0": [
        """GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007 Copyright (C) 2007 Free Software Foundation, Inc. Everyone is permitted to copy and distribute verbatim copies of this license document, but changing it is not allowed. Preamble The GNU General Public License is a free, copyleft license for software and other kinds of works."""
    ],
    "GPL-2.0": [
        """GNU GENERAL PUBLIC LICENSE Version 2, June 1991 Copyright (C) 1989, 1991 Free Software Foundation, Inc. Everyone is permitted to copy and distribute verbatim copies of this license document, but changing it is not allowed. Preamble The licenses for most software are designed to take away your freedom to share and change it."""
    ],
    "LGPL-3.0": [
        """GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007 Copyright (C) 2007 Free Software Foundation, Inc. Everyone is permitted to copy and distribute verbatim copies of this license document, but changing it is not allowed. This version of the GNU Lesser General Public License incorporates the terms and conditions of version 3 of the GNU General Public License, supplemented by the additional permissions listed below."""
    ],
    "MPL-2.0": [
        """Mozilla Public License Version 2.0 1. Definitions 1.1. "Contributor" means each individual or legal entity that creates, contributes to the creation of, or owns Covered Software. 1.2. "Contributor Version" means the combination of the Contributions of others (if any) used by a Contributor and that particular Contributor's Contribution."""
    ],
}
FILE_NAMES = ("license", "licence", "copying", "license.txt", "licence.txt", "license.md", "licence.md", "copying.txt")


def terms(text: str) -> list[str]:
    return WORD.findall(text.lower())


class Matcher:
    """Templates as unit vectors under document frequencies."""

    def __init__(self, templates: dict[str, list[str]], frequency: dict[str, int], n_docs: int, threshold: float):
        self.threshold, self.rarest = threshold, math.log(1 + n_docs) + 1
        self.idf = {t: math.log((1 + n_docs) / (1 + f)) + 1 for t, f in frequency.items()}
        self.vectors = []
        self.anchors: set[str] = set()
        self.own: list[tuple[int, set[str]]] = []  # terms and anchors of each template
        for name, texts in sorted(templates.items()):
            for text in texts:
                v = {t: n * self.idf.get(t, self.rarest) for t, n in Counter(terms(text)).items()}
                norm = math.sqrt(sum(x * x for x in v.values()))
                self.vectors.append((name, {t: x / norm for t, x in v.items()}))
                rest, mine = 0.0, set()
                for t, x in sorted(self.vectors[-1][1].items(), key=lambda p: (p[1], p[0])):
                    rest += x * x
                    if math.sqrt(rest) >= threshold:
                        mine.add(t)
                self.anchors |= mine
                self.own.append((len(terms(text)), mine))

    def best(self, unit: str) -> tuple[float, str]:
        """(cosine, name) of the nearest template; ties to the first name."""
        return self.best_of(terms(unit))

    def best_of(self, words: list[str]) -> tuple[float, str]:
        v = {t: n * self.idf.get(t, self.rarest) for t, n in Counter(words).items()}
        norm = math.sqrt(sum(x * x for x in v.values())) or 1.0
        cos = [(sum(x * v.get(t, 0.0) for t, x in vector.items()) / norm, name) for name, vector in self.vectors]
        top = max(c for c, _ in cos)
        return round(top, 9), min(name for c, name in cos if c == top)

    def windows(self, words: list[str]) -> Iterator[tuple[int, float, str]]:
        """(first template term, cosine, name) of each window of a template's length with an anchor, at or above the threshold."""
        w = [self.idf.get(t, self.rarest) for t in words]
        for (size, mine), (name, vector) in zip(self.own, self.vectors, strict=True):
            starts = sorted({s for p, t in enumerate(words) if t in mine for s in range(max(0, p - size + 1), min(p, len(words) - size) + 1)})
            count: Counter[str] = Counter()
            norm = dot = 0.0
            last = None
            for s in starts:
                if last is None or s - last >= size:
                    count.clear()
                    norm = dot = 0.0
                    out, new = (), range(s, s + size)
                else:
                    out, new = range(last, s), range(last + size, s + size)
                for i in out:
                    count[words[i]] -= 1
                    norm -= (2 * count[words[i]] + 1) * w[i] * w[i]
                    dot -= w[i] * vector.get(words[i], 0.0)
                for i in new:
                    norm += (2 * count[words[i]] + 1) * w[i] * w[i]
                    dot += w[i] * vector.get(words[i], 0.0)
                    count[words[i]] += 1
                last = s
                if dot >= (self.threshold - 1e-9) * math.sqrt(max(norm, 1e-300)) and (cos := round(dot / math.sqrt(norm), 9)) >= self.threshold:
                    yield next(i for i in range(s, s + size) if words[i] in vector), cos, name

    def notices(self, text: str) -> list[tuple[int, float, str]]:
        """(line, cosine, name) of the units at or above the threshold; a run or window counts at its first line."""
        return [(line, cos, name) for line, cos, name, _ in self.units(text)]

    def units(self, text: str) -> Iterator[tuple[int, float, str, list[str]]]:
        """The notices with their terms; those of a window with the terms of its template's length from the first on both sides."""
        if self.anchors.isdisjoint(terms(text)):
            return
        lines, run = text.split("\n"), []
        for i, line in enumerate([*lines, ""]):
            if i < len(lines) and not self.anchors.isdisjoint(terms(line)):
                run.append(i)
                continue
            parts = [(k, lines[k]) for k in run] + ([(run[0], "\n".join(lines[k] for k in run))] if len(run) > 1 else [])
            for k, unit in parts:
                cos, name = self.best(unit)
                if cos >= self.threshold:
                    yield k, cos, name, terms(unit)
            run = []
        words = [(t, i) for i, line in enumerate(lines) for t in terms(line)]
        longest, plain = max(n for n, _ in self.own), [t for t, _ in words]
        for at, cos, name in self.windows(plain):
            yield words[at][1], cos, name, plain[max(0, at - longest) : at + longest]


class FileMatcher(Matcher):
    """Whole licence files against whole licences and openings."""

    def __init__(self, templates: dict[str, list[str]], frequency: dict[str, int], n_docs: int, threshold: float):
        super().__init__(templates, frequency, n_docs, threshold)
        self.sizes = sorted({n for n, _ in self.own})

    def units(self, text: str) -> Iterator[tuple[int, float, str, list[str]]]:
        """As of a matcher: the whole file, and windows of each template's length at quarter steps."""
        words = [(t, i) for i, line in enumerate(text.split("\n")) for t in terms(line)]
        parts = {(0, len(words))} | {(k, k + n) for n in self.sizes for k in range(0, max(1, len(words) - n + 1), max(1, n // 4))}
        for a, b in sorted(parts):
            own = [t for t, _ in words[a:b]]
            cos, name = self.best_of(own)
            if own and cos >= self.threshold:
                yield words[a][1], cos, name, own


def is_license_file(path: str | None) -> bool:
    return (path or "").rsplit("/", 1)[-1].lower() in FILE_NAMES


def frequencies(docs: DataFrame, vocabulary: set[str], text_col: str = "text") -> tuple[dict[str, int], int]:
    """Documents with each term of the vocabulary, over all rows, and the number of rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter[str] = Counter()
        for batch in batches:
            for t in batch.column(0):
                seen.update(vocabulary.intersection(terms(t.as_py() or "")))
                seen[""] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["term", "n"])

    got = docs.select(text_col).mapInArrow(run, "term string, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    counts = {r["term"]: r["n"] for r in got}  # at most one row for each term of the templates
    n = counts.pop("", 0)
    return {t: counts.get(t, 0) for t in vocabulary}, n


def scan_licenses(files: DataFrame, id_col: str = "doc_id", text_col: str = "text", path_col: str = "path", threshold: float = 0.75, templates: dict[str, list[str]] | None = None, whole: dict[str, list[str]] | None = None, scratch: Scratch | None = None) -> DataFrame:
    """One row a file: (doc_id, path, own_license, own_similarity, own_line, license, license_dir).

    own_*: the file's best notice (ties to the first line), null without one. license: the own one, else that of the nearest ancestor directory
    (its own directory first) with a licence file, which is a file with a notice named as in FILE_NAMES; a directory with several
    takes the best, ties to the first path and name. license_dir says where an inherited one comes from. A null text counts as empty; a null
    path has no directory and inherits nothing; rows may repeat; other columns are ignored.
    """
    templates, whole = templates or TEMPLATES, FILE_TEMPLATES if whole is None else whole
    scratch = scratch or Scratch(files.sparkSession)
    vocabulary = {t for texts in [*templates.values(), *whole.values()] for text in texts for t in terms(text)}
    known, n_docs = frequencies(files, vocabulary, text_col)
    light = Matcher(templates, known, n_docs, threshold)
    light_whole = FileMatcher(whole, known, n_docs, threshold)
    light.rarest = light_whole.rarest = 1.0  # the least weight, of a term that every document has; the templates' own terms are all known

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[str] = set()
        for batch in batches:
            for t, path in zip(batch.column(0), batch.column(1), strict=True):
                for m in (light, light_whole)[: 1 + is_license_file(path.as_py())]:
                    for *_, words in m.units(t.as_py() or ""):
                        seen.update(words)
        yield pa.RecordBatch.from_arrays([pa.array(sorted(seen - vocabulary), pa.string())], ["term"])

    others = {r["term"] for r in files.select(text_col, path_col).mapInArrow(near, "term string").distinct().collect()}  # terms beside notices
    known |= frequencies(files, others, text_col)[0] if others else {}
    matchers = Matcher(templates, known, n_docs, threshold), FileMatcher(whole, known, n_docs, threshold)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = [(t.as_py() or "", matchers[: 1 + is_license_file(p.as_py())]) for p, t in zip(batch.column(1), batch.column(2), strict=True)]
            found = [min(((-c, k, n) for m in ms for k, c, n in m.notices(t)), default=None) for t, ms in own]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([f and f[2] for f in found], pa.string()), pa.array([f and -f[0] for f in found], pa.float64()), pa.array([f and f[1] for f in found], pa.int32())],
                ["doc_id", "path", "own_license", "own_similarity", "own_line"],
            )

    own = files.select(F.col(id_col).cast("long").alias("doc_id"), F.col(path_col).alias("path"), text_col).mapInArrow(run, "doc_id long, path string, own_license string, own_similarity double, own_line int")
    own = scratch.table(own.withColumn("dir", F.expr("regexp_replace(path, '/?[^/]*$', '')")), "own")
    n = own.count()
    named = F.lower(F.regexp_extract("path", "[^/]*$", 0)).isin(*FILE_NAMES)
    grants = own.where(named & F.col("own_license").isNotNull()).groupBy(F.col("dir").alias("license_dir")).agg(F.min_by("own_license", F.struct(-F.col("own_similarity"), "path", "own_license")).alias("license"))
    dirs = own.where("dir IS NOT NULL").groupBy("dir").agg(F.count("*").alias("n"))
    parts = F.split("dir", "/")
    ancestors = dirs.select("dir", F.explode(F.transform(F.sequence(F.lit(0), F.size(parts)), lambda k: F.struct(k.alias("depth"), F.concat_ws("/", F.slice(parts, 1, k)).alias("license_dir")))).alias("a")).select("dir", "a.*").distinct()
    nearest = ancestors.join(grants, "license_dir").groupBy("dir").agg(F.max_by(F.struct("license", "license_dir"), "depth").alias("from"))
    told = scratch.table(dirs.join(nearest, "dir", "left"), "dirs")
    rows = heavy_join(own.where("dir IS NOT NULL"), told, ["dir"], "n", n).drop("n").unionByName(own.where("dir IS NULL").withColumn("from", F.lit(None).cast("struct<license:string,license_dir:string>")))
    return rows.select("doc_id", "path", "own_license", "own_similarity", "own_line", F.coalesce("own_license", "from.license").alias("license"), F.when(F.col("own_license").isNull(), F.col("from.license_dir")).alias("license_dir"))
