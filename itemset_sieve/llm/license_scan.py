"""License scans: sparse TF-IDF cosines of statements to templates, then inheritance from ancestor directories.

Every sentence and every paragraph that holds a cue word is compared with all templates; a file's own license is
that of its best match. A licence file, by its name or because its whole text is close to a template, governs its
directory; a file without a license of its own takes that of the nearest directory above it that has one.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize

#: Short notices by which texts state their license, and openings of the licences themselves. Fixed values.
TEMPLATES = {
    "apache-2.0": ("Licensed under the Apache License, Version 2.0.", "Apache License Version 2.0, January 2004. Terms and conditions for use, reproduction, and distribution"),
    "mit": ("Released under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the software without restriction"),
    "gpl-3.0": ("This work is licensed under the GNU General Public License, version 3.", "GNU General Public License Version 3, 29 June 2007. Everyone is permitted to copy and distribute verbatim copies of this license document"),
    "gpl-2.0": ("This work is licensed under the GNU General Public License, version 2.",),
    "lgpl": ("Licensed under the GNU Lesser General Public License.",),
    "bsd-3-clause": ("Use of this source code is governed by a BSD-style license.", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    "mpl-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
    "cc-by-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "cc-by-sa-4.0": ("Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    "cc-by-nc-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "cc0-1.0": ("CC0 1.0 Universal. To the extent possible under law, the author has waived all copyright.",),
    "unlicense": ("This is free and unencumbered software released into the public domain.",),
    "all-rights-reserved": ("All rights reserved.",),
}
#: Only sentences and paragraphs with one of these are compared: a parameter of the scan. Every template has one.
CUES = re.compile(rb"licen[sc]e|copyright|rights reserved|public domain|creative commons|\bcc[ -]?(?:by|0)|permission is hereby|redistribution and use|spdx")
TERM = re.compile(rb"[a-z0-9]+(?:[.+-][a-z0-9]+)*")
SENTENCE = re.compile(rb"(?<=[.!?])\s+|\n")
PARAGRAPH = re.compile(rb"\n[\s#*/;-]*\n")
#: Names that make a file the licence of its directory.
LICENCE_NAME = r"(?i)^(licen[sc]e|copying|copyright|notice|unlicen[sc]e)([.-].*)?$"
#: Directories that are sent to every task at most; beyond, files of a directory are dealt over so many tasks.
BROADCAST, SPREAD = 200_000, 16
#: Least cosine of a statement.
CLOSE = 0.7
#: Least cosine of a whole text that makes its file a licence file whatever its name.
WHOLE = 0.92


def terms(text: bytes) -> Counter:
    return Counter(TERM.findall(text.lower()))


class Matcher:
    """Templates as sparse unit vectors under given document frequencies."""

    def __init__(self, n: int, df: dict[bytes, int]) -> None:
        self.idf = {t: math.log((1 + n) / (1 + c)) + 1 for t, c in df.items()}
        self.rare = math.log(1 + n) + 1  # of terms that no template has
        self.templates, self.by_term = [], {}
        for name, texts in TEMPLATES.items():
            for text in texts:
                vector, norm = self.vector(terms(text.encode()))
                for t, w in vector.items():
                    self.by_term.setdefault(t, []).append((len(self.templates), w / norm))
                self.templates.append(name)

    def vector(self, counts: Counter) -> tuple[dict, float]:
        v = {t: (1 + math.log(c)) * self.idf.get(t, self.rare) for t, c in counts.items()}
        return v, math.sqrt(sum(w * w for w in v.values()))

    def best(self, text: bytes) -> tuple[str | None, float]:
        """The closest template and its cosine; ties go to the name that sorts first."""
        v, norm = self.vector(terms(text))
        dots: dict[int, float] = {}
        for t, w in v.items():
            for k, u in self.by_term.get(t, ()):
                dots[k] = dots.get(k, 0.0) + w * u
        if not dots:
            return None, 0.0
        score, name = min((-round(d / norm, 9), self.templates[k]) for k, d in dots.items())
        return name, -score

    def own(self, text: bytes) -> tuple[str | None, float]:
        """The best statement of a text, over its sentences and paragraphs with cues."""
        low = text.lower()
        if not CUES.search(low):
            return None, 0.0
        found = (None, 0.0)
        for unit in dict.fromkeys((*SENTENCE.split(low), *PARAGRAPH.split(low))):
            if CUES.search(unit):
                name, score = self.best(unit)
                if score > found[1] or score == found[1] and name and found[0] and name < found[0]:
                    found = (name, score)
        return found if found[1] >= CLOSE else (None, found[1])


def frequencies(files: DataFrame) -> tuple[int, dict[bytes, int]]:
    """Number of files, and in how many of them each template term occurs: over all whole texts."""
    wanted = frozenset(t for texts in TEMPLATES.values() for x in texts for t in terms(x.encode()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, df = 0, Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                n += 1
                df.update(wanted.intersection(TERM.findall((text or b"").lower())))
        rows = [(b"", n), *df.items()]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.int64())], names=["term", "n"])

    rows = files.select("text").mapInArrow(run, "term binary, n long").groupBy("term").agg(F.sum("n")).collect()  # the templates' terms
    got = {bytes(r[0]): r[1] for r in rows}
    n = got.pop(b"", 0)
    return n, {t: got.get(t, 0) for t in wanted}


def parent(path):  # noqa: ANN001, ANN201
    """The directory of a path: '' at the root."""
    return F.regexp_replace(F.regexp_replace(path, r"[^/]*$", ""), r"/+$", "")


def scan(files: DataFrame, key: str = "path") -> DataFrame:
    """key, path, own_license, own_score, license, licensed_by of every row of files(path, text).

    licensed_by is the path itself, or the directory whose licence file it comes from; both null without any.
    Of several licence files in a directory the one with the highest cosine counts, then the first license by
    name. A null text is empty, a null path lies nowhere and inherits nothing. Rows that repeat are scanned each; texts of
    any length are scanned whole; other columns are not read; an empty table gives an empty result.
    """
    base = files.select(F.col(key).alias("_key"), F.col("path").cast("string").alias("path"), F.col("text").cast("string").cast("binary").alias("text"))
    shared = files.sparkSession.sparkContext.broadcast(Matcher(*frequencies(base)))  # the templates

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            names, scores, whole = [], [], []
            for text in batch.column(2).to_pylist():
                name, score = m.own(text or b"")
                names.append(name)
                scores.append(score)
                whole.append(bool(name) and m.best(text)[1] >= WHOLE)
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(whole, pa.bool_())], names=["_key", "path", "own", "score", "whole"])

    kind = base.schema["_key"].dataType.simpleString()
    own = materialize(base.mapInArrow(run, f"_key {kind}, path string, own string, score double, whole boolean"), "licenses").withColumn("dir", parent(F.col("path")))
    name = F.regexp_extract("path", r"[^/]*$", 0)
    stated = own.where(F.col("own").isNotNull() & F.col("path").isNotNull() & (F.col("whole") | name.rlike(LICENCE_NAME)))
    top = stated.groupBy("dir").agg(F.min(F.struct(-F.col("score"), F.col("own"))).alias("s")).select(F.col("dir").alias("above"), F.col("s.own").alias("given"))
    # Directories, not files, look upwards: each asks for itself and all directories above it.
    dirs = own.where("path is not null").select("dir").distinct()
    parts = F.split("dir", "/")
    ups = F.transform(F.sequence(F.lit(0), F.when(F.col("dir") == "", 0).otherwise(F.size(parts))), lambda n: F.array_join(F.slice(parts, F.lit(1), n), "/"))
    asked = dirs.select("dir", F.posexplode(ups).alias("depth", "above")).join(top, "above")
    near = asked.groupBy("dir").agg(F.max(F.struct("depth", "above", "given")).alias("n")).select("dir", F.col("n.above").alias("above"), F.col("n.given").alias("given"))
    near = materialize(near, "directories")
    if near.count() <= BROADCAST:
        out = own.join(F.broadcast(near), "dir", "left")
    else:  # a directory may hold very many files: they are dealt over several tasks
        spread = near.withColumn("_deal", F.explode(F.sequence(F.lit(0), F.lit(SPREAD - 1))))
        out = own.withColumn("_deal", F.pmod(F.xxhash64("_key", "path"), F.lit(SPREAD)).cast("int")).join(spread, ["dir", "_deal"], "left")
    by = F.when(F.col("own").isNotNull(), F.col("path")).otherwise(F.col("above"))
    return out.select(F.col("_key").alias(key if key != "path" else "file"), "path", F.col("own").alias("own_license"), F.col("score").alias("own_score"), F.coalesce("own", "given").alias("license"), by.alias("licensed_by"))


def document_files(docs: DataFrame) -> DataFrame:
    """Documents as files: each lies in the directory of its source and language."""
    return docs.withColumn("path", F.concat_ws("/", F.coalesce("source", F.lit("_")), F.coalesce("lang", F.lit("_")), F.concat(F.col("doc_id").cast("string"), F.lit(".txt"))))
