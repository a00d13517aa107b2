"""Licence scan: passages matched to templates by TF-IDF cosine, then handed down from licence files to what lies below them."""

from __future__ import annotations

import pkgutil
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, DoubleType, LongType, StringType, StructField, StructType

from .common import load, slices, small_batches, stored

#: Notices by licence; several for one licence are matched apart.
TEMPLATES: list[tuple[str, str]] = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License"),
    ("LGPL-3.0", "This library is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License"),
    ("AGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License"),
    ("LGPL-3.0", "Licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "Licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted"),
    ("BSD-3-Clause", "Use of this source code is governed by a BSD-style license."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC0-1.0", "Dedicated to the public domain under CC0 1.0."),
    ("Proprietary", "All rights reserved."),
]
PERMISSIVE = ("Apache-2.0", "MIT", "BSD-3-Clause", "CC-BY-4.0", "CC0-1.0", "MPL-2.0")
#: The word that names a licence: where a template has it, text without it is no match, however much of the rest is there.
NAMES = {"Apache-2.0": "apache", "MIT": "mit", "GPL-3.0": "gnu", "LGPL-3.0": "lesser", "AGPL-3.0": "affero", "BSD-3-Clause": "bsd", "MPL-2.0": "mozilla", "CC-BY-4.0": "cc", "CC-BY-SA-4.0": "sa", "CC-BY-NC-4.0": "nc", "CC0-1.0": "cc0", "Proprietary": "reserved"}
_TOKEN = re.compile(r"[^\W_]+")


def _full(name: str) -> str:
    return (pkgutil.get_data(__package__, f"license_texts/{name}.txt") or b"").decode()


#: Whole licences, compared with whole files. That of AGPL-3.0 is the text of GPL-3.0 with the other name, from which it differs in a few paragraphs.
FULL: list[tuple[str, str]] = [(x, _full(x)) for x in ("Apache-2.0", "BSD-3-Clause", "CC0-1.0", "GPL-3.0", "LGPL-3.0", "MIT", "MPL-2.0")]
FULL.append(("AGPL-3.0", re.sub("(?i)GNU General Public", "GNU Affero General Public", dict(FULL)["GPL-3.0"])))
LICENCES = [x for x, _ in TEMPLATES + FULL]
VOCABULARY = sorted({w for _, t in TEMPLATES + FULL for w in _TOKEN.findall(t.lower())})


def document_counts(docs: DataFrame, text_column: str = "text") -> tuple[int, DataFrame]:
    """Number of documents and (word, n): of every word of the texts, the documents that have it; a task's rows are summed before they are dealt out by word."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])
            seen.clear()
            return out

        total, seen = 0, Counter()
        for batch in slices(batches):
            for text in batch.column("text").to_pylist():
                total += 1
                seen.update(set(_TOKEN.findall((text or "").lower())))
            if len(seen) > 100_000:
                yield rows()
        seen[None] = total
        yield rows()

    found = docs.select(F.col(text_column).cast("string").alias("text")).mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    counts = stored(found, "words")
    (total,) = counts.filter("word is null").agg(F.coalesce(F.sum("n"), F.lit(0))).first()
    return total, counts.filter("word is not null")


def known_counts(total: int, counts: DataFrame) -> dict[str, int]:
    """Of the words of the templates, and of those that a hundredth of the documents have: at most a hundred times as many as a document has."""
    return {r["word"]: r["n"] for r in counts.filter(F.col("word").isin(*VOCABULARY) | (100 * F.col("n") >= total)).collect()}


class Matcher:
    """Cosine of lines with templates; the weight of a word is log((1 + documents) / (1 + documents with the word)) + 1.

    A word of no template that ``counts`` lacks is missing: with it a cosine is an upper bound (no weight
    is below 1), and if that reaches the threshold, its number of documents has to be looked up.
    """

    def __init__(self, total: int, counts: dict[str, int], threshold: float):
        self.total, self.threshold = total, threshold
        self.weights = {w: self.weight(n) for w, n in {**dict.fromkeys(VOCABULARY, 0), **counts}.items()}
        self.vectors: list[dict[str, float]] = []
        self.postings: dict[str, list[int]] = {}
        self.sizes: list[int] = []
        for k, (licence, text) in enumerate(TEMPLATES):
            tokens = _TOKEN.findall(text.lower())
            v = {w: n * self.weights[w] for w, n in Counter(tokens).items()}
            norm = sum(x * x for x in v.values()) ** 0.5
            self.vectors.append({w: x / norm for w, x in v.items()})
            self.sizes.append(len(tokens))
            for w in [NAMES[licence]] if NAMES[licence] in v else self.anchors(self.vectors[k]):
                self.postings.setdefault(w, []).append(k)
        self.full: dict[str, list[int]] = {}
        for k, (_, text) in enumerate(FULL, len(TEMPLATES)):
            v = {w: (1 + float(np.log(n))) * self.weights[w] for w, n in Counter(_TOKEN.findall(text.lower())).items()}
            norm = sum(x * x for x in v.values()) ** 0.5
            self.vectors.append({w: x / norm for w, x in v.items()})
            for w in v:
                self.full.setdefault(w, []).append(k)

    def weight(self, n: int) -> float:
        return float(np.log((1 + self.total) / (1 + n)) + 1)

    def anchors(self, vector: dict[str, float]) -> list[str]:
        """The heaviest words of a template, so many that text with none of them stays below the threshold, whatever else it has."""
        words = sorted(vector, key=lambda w: (-vector[w], w))
        rest = 1.0
        for i, w in enumerate(words):
            if rest < self.threshold**2 - 1e-9:
                return words[:i]
            rest -= vector[w] ** 2
        return words

    def compare(self, tokens: list[str], k: int, looked_up: dict[str, int]) -> tuple[float, list[str]]:
        """Cosine with a template, or its upper bound, and the missing words. With a whole licence, a word's number counts as 1 + log of it, for else the commonest words decide."""
        vector, dot, norm, missing = self.vectors[k], 0.0, 0.0, []
        for w, n in Counter(tokens).items():
            x = self.weights.get(w)
            if x is None:
                if w in looked_up:
                    x = self.weight(looked_up[w])
                else:
                    missing.append(w)
                    x = 1.0
            if k >= len(TEMPLATES):
                n = 1 + float(np.log(n))
            norm += (n * x) ** 2
            if w in vector:
                dot += n * x * vector[w]
        return round(dot / norm**0.5, 12), missing

    def hits(self, tokens: list[str], looked_up: dict[str, int], missing: set[str], longer: int = 0) -> list[tuple[float, int, int, int]]:
        """(-cosine, template, start, end) of all windows, as long as their template or the whole of shorter ``tokens``, that can reach the threshold; only of templates of at least ``longer`` words."""
        at: dict[int, list[int]] = {}
        for i, w in enumerate(tokens):
            for k in self.postings.get(w, ()):
                at.setdefault(k, []).append(i)
        out = []
        for k, places in at.items():
            vector, size, starts = self.vectors[k], self.sizes[k], set()
            if size < longer:
                continue
            for i in places:
                low, high = max(0, i - size + 1), max(0, min(i, len(tokens) - size))
                near = vector.keys() & set(tokens[low : high + size])
                if sum(vector[w] ** 2 for w in near) >= self.threshold**2 - 1e-9:
                    starts.update(range(low, high + 1))
            for i in sorted(starts):
                cosine, lacks = self.compare(tokens[i : i + size], k, looked_up)
                if cosine >= self.threshold:
                    missing.update(lacks)
                    out.append((-cosine, k, i, min(i + size, len(tokens))))
        return out

    def whole(self, tokens: list[str], distinct: set[str], looked_up: dict[str, int], missing: set[str]) -> tuple[float, int]:
        """(cosine, template) of the whole licence nearest to a whole file, the first of equals; (0, -1) if none can reach the threshold."""
        shares: dict[int, float] = {}
        for w in self.full.keys() & distinct:
            for k in self.full[w]:
                shares[k] = shares.get(k, 0.0) + self.vectors[k][w] ** 2
        best = (0.0, -1)
        for k in sorted(k for k, x in shares.items() if x >= self.threshold**2 - 1e-9):
            cosine, lacks = self.compare(tokens, k, looked_up)
            if cosine >= self.threshold:
                missing.update(lacks)
                best = max(best, (cosine, k), key=lambda r: (r[0], -r[1]))
        return best

    def text(self, text: str, looked_up: dict[str, int]) -> tuple[int, int, float, int, list[str], bool]:
        """(lines, lines that match, best cosine, its template, missing words, licence file?); all but the missing words hold if there are none.

        Windows run on over the ends of lines; a line shorter than a template is also compared alone. Of overlapping windows the best one counts, and its lines match.
        """
        lines = [x for x in text.split("\n") if x.strip()]
        tokens = _TOKEN.findall(text.lower())
        distinct, missing = set(tokens), set()
        best, which = self.whole(tokens, distinct, looked_up, missing)
        is_whole, matched = which >= 0, set()
        if not self.postings.keys().isdisjoint(distinct):
            parts = [_TOKEN.findall(x.lower()) for x in lines]
            found, line_of = self.hits(tokens, looked_up, missing), []
            for i, part in enumerate(parts):
                if not self.postings.keys().isdisjoint(part):
                    start = len(line_of)
                    found += [(c, k, start + a, start + b) for c, k, a, b in self.hits(part, looked_up, missing, len(part) + 1)]
                line_of += [i] * len(part)
            taken = set()
            for c, k, a, b in sorted(found):
                if taken.isdisjoint(range(a, b)):
                    taken.update(range(a, b))
                    matched.update(line_of[a:b])
            if found and not is_whole:
                c, _, which = min((c, a, k) for c, k, a, _ in found)
                best = -c
            is_whole |= all(i in matched for i, part in enumerate(parts) if part)
        return len(lines), len(matched), best, which, sorted(missing), is_whole


def scan(files: DataFrame, path_column: str = "path", text_column: str = "text", threshold: float = 0.7) -> DataFrame:
    """Add ``own_license``, ``similarity``, ``n_lines``, ``n_matched``, ``license``, ``inherited_from`` and ``permissive`` to ``files``.

    Every text is compared as a whole with the whole licences, and a window as long as each notice
    slides over its words, across lines, near the notice's name or rare words. A whole licence of at
    least ``threshold`` is the file's own licence, else the nearest notice (of equals the first in the text, then the
    first template). The few texts whose verdict hangs on words that few documents have are judged once those words'
    counts are joined to them. A file that is a whole licence, or of which every line with a word is part of a notice,
    is the licence file of its directory (of several in one directory
    that with the highest cosine, then the smallest path). A file without own licence takes that of
    the nearest directory above it that has a licence file: the directories above a path, as many
    as it is deep, meet the licence files by an equi-join. Null and empty texts have no licence of
    their own; a null path inherits nothing; columns of the results' names are replaced.
    """
    new = [StructField("n_lines", LongType()), StructField("n_matched", LongType()), StructField("similarity", DoubleType()), StructField("own_license", StringType())]
    files = files.drop(*(f.name for f in new), "license", "inherited_from", "permissive", "__row", "__missing", "__text", "__counts", "__whole")
    small_batches(files.sparkSession)
    total, counts = document_counts(files, text_column)
    known = known_counts(total, counts)
    kept = [f for f in files.schema.fields if f.name != text_column]
    undecided = [StructField("__row", StringType()), StructField("__missing", ArrayType(StringType())), StructField("__text", StringType())]
    columns_of = StructType([*kept, *new, StructField("__whole", BooleanType()), *undecided])

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher, part, at = Matcher(total, known, threshold), TaskContext.get().partitionId(), 0
        for batch in slices(batches, column=text_column):
            texts = [x or "" for x in batch.column(text_column).to_pylist()]
            looked_up = [dict(x) for x in batch.column("__counts").to_pylist()] if "__counts" in batch.schema.names else [{}] * len(texts)
            rows = [matcher.text(*x) for x in zip(texts, looked_up)]
            columns = [pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.float64()), pa.array([LICENCES[r[3]] if r[3] >= 0 else None for r in rows], pa.string()), pa.array([r[5] for r in rows], pa.bool_())]
            columns += [pa.array([f"{part}-{at + i}" for i in range(len(rows))]), pa.array([r[4] or None for r in rows], pa.list_(pa.string())), pa.array([x if r[4] else None for x, r in zip(texts, rows)], pa.string())]
            at += len(rows)
            yield pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in kept), *columns], columns_of.names)

    first = stored(files.withColumn(text_column, F.col(text_column).cast("string")).mapInArrow(match, columns_of), "licences")
    open_rows = first.filter("__missing is not null")
    entries = open_rows.select("__row", F.explode("__missing").alias("word")).join(counts, "word").groupBy("__row").agg(F.collect_list(F.struct("word", "n")).alias("c"))
    again = open_rows.select("__row", *(f.name for f in kept), F.col("__text").alias(text_column)).join(entries.select("__row", F.map_from_entries("c").alias("__counts")), "__row").drop("__row")
    own = stored(first.filter("__missing is null").drop("__row", "__missing", "__text").unionByName(again.mapInArrow(match, columns_of).drop("__row", "__missing", "__text")), "licences")
    directory = F.regexp_replace(F.col(path_column), "/?[^/]*$", "")
    notices = own.filter(F.col(path_column).isNotNull() & F.col("own_license").isNotNull() & F.col("__whole"))
    best = F.min(F.struct((-F.col("similarity")).alias("s"), F.col(path_column).alias("p"), F.col("own_license").alias("l")))
    holders = notices.groupBy(directory.alias("directory")).agg(best.alias("b")).select("directory", F.col("b.p").alias("holder"), F.col("b.l").alias("held"))
    needing = own.filter(F.col("own_license").isNull() & F.col(path_column).isNotNull()).select(directory.alias("below")).distinct()
    steps = F.expr("transform(sequence(0, size(split(below, '/'))), k -> struct(k AS depth, array_join(slice(split(below, '/'), 1, k), '/') AS directory))")
    above = needing.select("below", F.explode(F.filter(steps, lambda s: (s["depth"] == 0) | (s["directory"] != ""))).alias("s")).select("below", "s.depth", "s.directory").distinct()
    nearest = above.join(holders, "directory").groupBy("below").agg(F.max(F.struct("depth", "holder", "held")).alias("n")).select("below", "n.holder", "n.held")
    out = own.withColumn("below", F.when(F.col("own_license").isNull(), directory)).join(nearest, "below", "left")
    out = out.withColumn("license", F.coalesce("own_license", "held")).withColumn("inherited_from", F.when(F.col("own_license").isNull(), F.col("holder")))
    return out.withColumn("permissive", F.coalesce(F.col("license").isin(*PERMISSIVE), F.lit(False))).drop("below", "holder", "held", "__whole")


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as files: the source is the top directory, below it one directory for each 64 neighbouring ids."""
    docs = load(spark, sf_dir, "documents")
    path = F.concat_ws("/", "source", F.concat(F.lit("d"), F.floor(F.col("doc_id") / 64)), F.concat(F.col("doc_id"), F.lit(".txt")))
    return scan(docs.select("doc_id", path.alias("path"), "text"))
