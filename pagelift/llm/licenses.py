"""Licence scan: sparse TF-IDF cosine of text passages to licence templates, then inheritance along directories.

A passage is a line, or a window of a long line.  Terms are lower-cased runs of letters and digits.  Document frequencies
of all terms are counted over all passages of the corpus.  A template is compared with whole passages, and with the
windows of about its own length (REACH times at most) at every place of every line, so further words on a line cost a
notice nothing.  In licence files windows also run across line ends, and the whole file is compared.  A passage whose
cosine to a template reaches the threshold states that licence; a file's licence is its best passage's.

A template can't be reached by words that hold less than THRESHOLD**2 of its squared length, so most texts and lines are
left after a look at their template terms.  Terms of more than 1/COMMON of the passages are at most WINDOW * COMMON; they
are broadcast.  Passages that may state a licence, by the bounds of their other terms' weights, are joined with the
frequencies of these: no such term is frequent, so no task is.

A licence found in a licence file (by name) holds for its directory.  A file without a licence of its own takes that of
the nearest ancestor directory that has one: directories, not files, are expanded into their ancestors and joined with
the licensed directories by path; files then join on their directory.

Defined results: null texts state nothing; a file with a null path inherits nothing; of several licence files in one
directory the best score counts, then the smaller name; rows that share an id are reported each; the score is that of
the own licence, and null without one.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm.common import cut, thrifty

#: The usual one-line notices, by SPDX identifier.
TEMPLATES = {
    "Apache-2.0": ("Licensed under the Apache License, Version 2.0.", "SPDX-License-Identifier: Apache-2.0"),
    "BSD-3-Clause": ("Licensed under the BSD 3-Clause License.", "SPDX-License-Identifier: BSD-3-Clause"),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC0-1.0": ("To the extent possible under law, all copyright and related rights are waived under CC0 1.0.",),
    "GPL-3.0": ("This work is licensed under the GNU General Public License, version 3.", "SPDX-License-Identifier: GPL-3.0-only"),
    "LicenseRef-All-Rights-Reserved": ("All rights reserved.",),
    "LGPL-3.0": ("This work is licensed under the GNU Lesser General Public License, version 3.",),
    "MIT": ("Released under the MIT License.", "SPDX-License-Identifier: MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software"),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
}
NAMES = ("license", "licence", "copying", "notice", "unlicense")
TERM = re.compile(r"[^\W_]+")
WINDOW, STEP = 32, 8
THRESHOLD = 0.75
REACH = 1.5
COMMON = 2000
PENDING = 100_000  # distinct terms that a task counts before it hands them on
VOCABULARY = sorted({t for texts in TEMPLATES.values() for x in texts for t in TERM.findall(x.lower())})


def passages(text: str | None) -> Iterator[list[str]]:
    """Term lists of the lines; windows of WINDOW terms for longer lines."""
    for line in (text or "").lower().split("\n"):
        terms = TERM.findall(line)
        if len(terms) <= WINDOW:
            if terms:
                yield terms
        else:
            for at in range(0, len(terms) - WINDOW + STEP, STEP):
                yield terms[at : at + WINDOW]


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    n: Counter = Counter()
    total = 0

    def told() -> pa.RecordBatch:
        out = pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64())], names=["term", "n"])
        n.clear()
        return out

    for batch in thrifty(batches):
        for text in batch.column("text").to_pylist():
            for terms in passages(text):
                total += 1
                n.update(set(terms))
        if len(n) > PENDING:
            yield told()
    n[""] += total  # the number of passages
    yield told()


def weight(total, n):
    """Inverse document frequency of a term of n out of total passages."""
    return math.log((1 + total) / (1 + n)) + 1


class Matcher:
    """Cosines by the frequencies of common terms; any other term has 1 to total/share passages."""

    def __init__(self, counts: dict[str, int], share: int = COMMON):
        total = counts.get("", 0)
        self.idf = {t: weight(total, n) for t, n in counts.items() if t}
        self.idf |= {t: weight(total, 0) for t in VOCABULARY if t not in counts}
        self.least, self.most = weight(total, max(1, total / share)), weight(total, 1)
        self.known, self.templates = frozenset(VOCABULARY), []
        for name, texts in sorted(TEMPLATES.items()):
            for text in texts:
                terms = TERM.findall(text.lower())
                v = {t: (1 + math.log(n)) * self.idf[t] for t, n in Counter(terms).items()}
                norm = math.sqrt(sum(x * x for x in v.values()))
                self.templates.append((name, {t: x / norm for t, x in v.items()}, len(terms)))

    def within_reach(self, terms, templates: list) -> list:
        """The templates whose cosine to some of these terms may reach the threshold."""
        hits = self.known.intersection(terms)
        return [t for t in templates if sum(t[1].get(x, 0.0) ** 2 for x in hits) >= THRESHOLD**2 * 0.999999] if hits else []

    def compare(self, terms: list[str], template: dict[str, float]) -> tuple[float, float, list[tuple[str, float]]]:
        """Dot product, squared length of the terms of known weight, and the others with the factors of their weights."""
        dot = size = 0.0
        others = []
        for t, n in Counter(terms).items():
            w = 1 + math.log(n)
            if t in self.idf:
                w *= self.idf[t]
                size += w * w
                dot += w * template.get(t, 0.0)
            else:
                others.append((t, w))
        return dot, size, others

    def pieces(self, terms: list[str], length: int) -> Iterator[list[str]]:
        """Runs of about a template's length that start and end with a template term, or are as short as the template."""
        at = [i for i, t in enumerate(terms) if t in self.known]
        longest = math.ceil(REACH * length)
        for i in at:
            first = max(0, min(i, len(terms) - length))
            yield terms[first : first + length]
            for j in at:
                if length < j + 1 - i <= longest:
                    yield terms[i : j + 1]

    def candidates(self, text: str, whole: bool) -> Iterator[tuple[tuple, list[str]]]:
        near = self.within_reach(TERM.findall(text), self.templates)
        if not near:
            return
        lines = [TERM.findall(line) for line in text.split("\n")]
        if whole and len(lines) > 1:
            lines.append([t for line in lines for t in line])
        for terms in lines:
            for template in self.within_reach(terms, near):
                yield template, terms
                if len(terms) > WINDOW:
                    yield from ((template, terms[at : at + WINDOW]) for at in range(0, len(terms) - WINDOW + STEP, STEP))
                yield from ((template, x) for x in self.pieces(terms, template[2]))

    def best(self, text: str | None, whole: bool = False) -> tuple[str | None, float | None, list[dict]]:
        """Licence and score by the known weights, and the passages that may state a better one."""
        name, top, left, seen = None, 0.0, {}, set()
        for (label, template, _), terms in self.candidates((text or "").lower(), whole):
            key = (label, id(template), tuple(sorted(terms)))
            if key in seen:
                continue
            seen.add(key)
            dot, size, others = self.compare(terms, template)
            if not others:
                if (cosine := dot / math.sqrt(size)) > top:
                    name, top = label, cosine
            elif dot / math.sqrt(size + sum((w * self.least) ** 2 for _, w in others)) >= THRESHOLD * 0.999999:
                left[key] = (label, dot, size, others)
        # what is surely not the best needs no join
        bound = lambda x, rest: x[1] / math.sqrt(x[2] + sum((w * rest) ** 2 for _, w in x[3]))
        sure = max([top, *(bound(x, self.most) for x in left.values())])
        open_ = [{"label": x[0], "dot": x[1], "size": x[2], "terms": [t for t, _ in x[3]], "factors": [w for _, w in x[3]]} for x in left.values() if bound(x, self.least) >= sure * 0.999999]
        return (name, top, open_) if top >= THRESHOLD else (None, None, open_)


def is_license_file(path: str | None) -> bool:
    return re.sub(r"\..*$", "", (path or "").split("/")[-1]).lower() in NAMES


OPEN = pa.list_(pa.struct([("label", pa.string()), ("dot", pa.float64()), ("size", pa.float64()), ("terms", pa.list_(pa.string())), ("factors", pa.list_(pa.float64()))]))
FOUND = "row long, doc_id long, path string, own string, score double, open array<struct<label: string, dot: double, size: double, terms: array<string>, factors: array<double>>>"


def detect(spark: SparkSession, files: DataFrame) -> DataFrame:
    """files (doc_id, path, text) -> doc_id, path, own, score."""
    share = COMMON
    files = files.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("path").cast("string").alias("path"), F.col("text").cast("string").alias("text"))
    counts = cut(spark, files.select("text").mapInArrow(_frequencies, "term string, n long").groupBy("term").agg(F.sum("n").alias("n")), "frequencies")
    total = counts.where("term = ''").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    common = spark.sparkContext.broadcast({r[0]: r[1] for r in counts.where(F.col("term").isin("", *VOCABULARY) | (F.col("n") * share > total)).collect()})  # at most WINDOW * share terms

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(common.value, share)
        for batch in thrifty(batches):
            found = [matcher.best(t, is_license_file(p)) for t, p in zip(batch.column("text").to_pylist(), batch.column("path").to_pylist())]
            own, score, left = ([x[k] for x in found] for k in range(3))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("row", "doc_id", "path")), pa.array(own, pa.string()), pa.array(score, pa.float64()), pa.array(left, OPEN)], names=["row", "doc_id", "path", "own", "score", "open"])

    found = cut(spark, files.withColumn("row", F.monotonically_increasing_id()).mapInArrow(stream, FOUND), "passages")
    left = found.where(F.size("open") > 0).select("row", F.posexplode("open").alias("at", "p"))
    terms = left.select("row", "at", "p.label", "p.dot", "p.size", F.explode(F.arrays_zip("p.terms", "p.factors")).alias("t")).select("row", "at", "label", "dot", "size", F.col("t.terms").alias("term"), F.col("t.factors").alias("factor"))
    part = F.col("factor") * (F.log((F.lit(1.0) + total) / (F.lit(1.0) + F.col("n"))) + 1)
    cosines = terms.join(counts, "term").groupBy("row", "at").agg(F.first("label").alias("label"), (F.first("dot") / F.sqrt(F.first("size") + F.sum(part * part))).alias("cosine")).where(F.col("cosine") >= THRESHOLD)
    better = cosines.groupBy("row").agg(F.max("cosine").alias("cosine"), F.min_by("label", F.struct(-F.col("cosine"), "label")).alias("label"))
    wins = F.col("cosine").isNotNull() & (F.col("score").isNull() | (F.col("cosine") > F.col("score")))
    out = found.drop("open").join(better, "row", "left")
    return out.select("doc_id", "path", F.when(wins, F.col("label")).otherwise(F.col("own")).alias("own"), F.when(wins, F.col("cosine")).otherwise(F.col("score")).alias("score"))


def inherit(found: DataFrame) -> DataFrame:
    """doc_id, path, license, origin (own, inherited or none), license_dir, score."""
    parts = F.split("path", "/")
    base = found.withColumn("dir", F.array_join(F.slice(parts, 1, F.greatest(F.size(parts) - 1, F.lit(0))), "/")).withColumn("name", F.lower(F.regexp_replace(F.element_at(parts, -1), r"\..*$", "")))
    stated = base.where(F.col("name").isin(*NAMES) & F.col("own").isNotNull())
    licensed = stated.groupBy("dir").agg(F.min_by("own", F.struct(-F.col("score"), "own")).alias("license")).select(F.col("dir").alias("license_dir"), "license")
    levels = F.split("dir", "/")
    up = F.concat(F.array(F.lit("")), F.transform(F.sequence(F.lit(1), F.size(levels)), lambda i: F.array_join(F.slice(levels, F.lit(1), i), "/")))
    above = base.where("dir IS NOT NULL").select("dir").distinct().select("dir", F.posexplode(up).alias("depth", "license_dir"))
    nearest = above.join(licensed, "license_dir").groupBy("dir").agg(F.max_by(F.struct("license", "license_dir"), "depth").alias("n"))
    out = base.join(nearest, "dir", "left")
    return out.select(
        "doc_id",
        "path",
        F.coalesce("own", "n.license").alias("license"),
        F.when(F.col("own").isNotNull(), "own").when(F.col("n").isNotNull(), "inherited").otherwise("none").alias("origin"),
        F.when(F.col("own").isNull(), F.col("n.license_dir")).alias("license_dir"),
        "score",
    )


def scan(spark: SparkSession, files: DataFrame) -> DataFrame:
    return inherit(cut(spark, detect(spark, files), "licenses"))


def tree_path(doc_id: Column) -> Column:
    """A place in a made-up tree, as the documents table has no paths.  Every 500th document is a project's licence file
    and every 25th a folder's."""
    project, folder = F.floor(doc_id / 500).cast("string"), F.floor(doc_id / 25).cast("string")
    plain = F.concat_ws("/", project, folder, F.concat(doc_id.cast("string"), F.lit(".txt")))
    return F.when(doc_id % 500 == 0, F.concat_ws("/", project, F.lit("LICENSE"))).when(doc_id % 25 == 0, F.concat_ws("/", project, folder, F.lit("LICENSE.txt"))).otherwise(plain)
