"""Licence scan by sparse TF-IDF cosine to templates and inheritance from the nearest ancestor directory, with DataFrame functions only.

Units of a file are its lines, its paragraphs and its whole text. A unit states a licence if the cosine of its term weights to a
template's reaches ``threshold``. A file whose whole text does, or reaches ``FULL`` to a full licence text, both without stop words, is a licence file of its directory. A file without a
statement of its own takes the licence of the nearest directory above it that has a licence file.

Inverse document frequencies come from the templates; a term in none of them weighs as one of document frequency 0. Before
anything is multiplied, units are filtered by a bound that loses nothing: of each template some terms, common words first, are so
light together that they can't reach the threshold, so a match holds one of its other terms.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from functools import reduce
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairsample.llm.common import Scratch

# Opening sentences and usual notices of public licences.
TEMPLATES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("Apache-2.0", "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/ TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "MIT License Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License version 2"),
    ("LGPL-3.0", "GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("All-rights-reserved", "All rights reserved."),
]
#: Common words, which are the first to do without when a match must hold one of a template's other terms.
COMMON = tuple("the of and to in a is that are by this it for was with as be on at or from not all any may use you into without work".split())
#: Words without weight where whole files are compared with full licence texts, of which they would make up most.
STOP = frozenset(COMMON) | frozenset(
    "an if such your other which we our these those its but have has had no so will shall may can one two they them their there who when where while than then also "
    "only each either more most must do does did been being within under over between through about out up s c".split()
)
#: Cosine that a whole file must reach to a full licence text.
FULL = 0.9
TERM = r"[a-z0-9]+(?:[.-][a-z0-9]+)*"


def terms(text: str) -> list[str]:
    return re.findall(TERM, re.sub("[A-Z]", lambda m: m.group().lower(), text))


def full_texts() -> list[tuple[str, str]]:
    """The full licence texts of the folder ``licenses``, compared with whole files only."""
    return [(p.stem, p.read_text(encoding="utf-8")) for p in sorted((Path(__file__).parent / "licenses").glob("*.txt"))]


class Weights:
    """Unit vectors of the templates, the weight of each known term, that of any other, and the terms one of which a match must hold."""

    def __init__(self, templates: list[tuple[str, str]], threshold: float, by: Weights | None = None, without: frozenset[str] = frozenset()) -> None:
        """``by`` gives the weights of terms, if not the templates themselves; terms of ``without`` weigh nothing."""
        bags = [Counter(t for t in terms(text) if t not in without) for _, text in templates]
        df = Counter(t for bag in bags for t in bag)
        self.idf = by.idf if by else {t: math.log((1 + len(bags)) / (1 + n)) + 1 for t, n in sorted(df.items())}
        self.other = by.other if by else math.log(1 + len(bags)) + 1
        self.vectors = []
        self.names = [name for name, _ in templates]
        #: Of each template some sets of its heaviest terms: without any of one set, too little weight is left for a match.
        self.sets: list[list[list[str]]] = []
        needed = set()
        for k, ((name, _), bag) in enumerate(zip(templates, bags, strict=True)):
            weight = {t: n * self.idf.get(t, self.other) for t, n in sorted(bag.items())}
            norm = math.sqrt(sum(w * w for w in weight.values()))
            self.vectors += [(k, name, t, w / norm) for t, w in weight.items()]
            rest = 0.0
            light = set()
            for t, w in sorted(weight.items(), key=lambda x: (COMMON.index(x[0]) if x[0] in COMMON else len(COMMON), x[1], x[0])):
                if rest + (w / norm) ** 2 < (threshold - 1e-9) ** 2:
                    rest += (w / norm) ** 2
                    light.add(t)
            needed |= set(weight) - light
            sets: list[list[str]] = []
            left = 0.0
            for t, w in sorted(weight.items(), key=lambda x: (-x[1], x[0])):
                if not sets or left > 1 - (threshold - 1e-9) ** 2:
                    sets.append([])
                    left = 0.0
                sets[-1].append(t)
                left += (w / norm) ** 2
            self.sets.append(sets if left > 1 - (threshold - 1e-9) ** 2 else sets[:-1] or [sorted(weight)])
        self.needed = sorted(needed)

    def pattern(self) -> str:
        return one_of(self.needed)

    def may_match(self, text: Column) -> Column:
        """Whether a text holds a term of each of the first four sets of some template."""
        if not self.sets:
            return F.lit(False)
        every = [reduce(Column.__and__, [text.rlike(one_of(terms)) for terms in sets[:4]]) for sets in self.sets]
        return text.rlike(one_of(sorted({t for sets in self.sets for t in sets[0]}))) & reduce(Column.__or__, every)


def one_of(found: list[str]) -> str:
    """The pattern of one of some terms as a whole term, the terms grouped by their first character."""
    groups: dict[str, list[str]] = {}
    for t in found:
        groups.setdefault(t[0], []).append(re.escape(t[1:]).replace("\\-", "-"))
    return "(?:^|[^a-z0-9])(?:" + "|".join(f"{c}(?:{'|'.join(rest)})" for c, rest in groups.items()) + ")(?:$|[^a-z0-9])"


def scan_licenses(
    files: DataFrame, id_col: str = "doc_id", path_col: str = "path", text_col: str = "text",
    threshold: float = 0.7, templates: list[tuple[str, str]] | None = None,
) -> DataFrame:
    """The licence of every file.

    Returns (id_col, path, license, basis, score, from_path): basis is ``file`` (the whole text is a licence), ``statement``
    (a line or paragraph is), ``inherited`` (from the licence file ``from_path``) or ``none``; score is the cosine, rounded to
    6 places, null for none. Of several statements the best score counts, then the smaller template name; of several licence files in a
    directory the smaller path. Null paths count as the root, null or empty texts state nothing; rows that repeat an id and a
    path get the best of their texts. An empty table gives an empty one; other columns are not read.
    """
    spark: SparkSession = files.sparkSession
    scratch = Scratch(spark, "licenses")
    known = Weights(templates or TEMPLATES, threshold)
    full = Weights([] if templates else full_texts(), FULL, known, STOP)
    # a row for each term: its weight, and its place in the vector of every template, full texts last
    vectors = {t: [None] * (len(known.names) + len(full.names)) for t in {*known.idf, *(t for _, _, t, _ in full.vectors), *STOP}}
    for shift, of in ((0, known), (len(known.names), full)):
        for k, _, t, w in of.vectors:
            vectors[t][shift + k] = w
    by_term = spark.createDataFrame([(t, known.idf.get(t, known.other), t in STOP, v) for t, v in sorted(vectors.items())], "term string, idf double, stop boolean, w array<double>")
    names = known.names + full.names
    own = files.select(F.col(id_col).cast("long").alias("d"), F.coalesce(F.col(path_col).cast("string"), F.lit("/")).alias("path"), F.lower(F.col(text_col).cast("string")).alias("text"))
    hit = own.where(F.col("text").rlike(known.pattern()) | full.may_match(F.col("text")))
    lines = F.transform(F.split("text", "\n"), lambda x: F.struct(F.lit("statement").alias("kind"), x.alias("unit")))
    # a text without a blank line is its only paragraph, and its whole is compared anyway
    cut = F.split("text", r"\n[ \t\r]*\n")
    paragraphs = F.when(F.size(cut) > 1, F.transform(cut, lambda x: F.struct(F.lit("statement").alias("kind"), x.alias("unit")))).otherwise(F.array().cast("array<struct<kind:string,unit:string>>"))
    whole = F.array(F.struct(F.lit("file").alias("kind"), F.col("text").alias("unit")))
    units = hit.select("d", "path", F.posexplode(F.concat(lines, paragraphs, whole)).alias("u", "x")).where(F.col("x.unit").rlike(known.pattern()) | ((F.col("x.kind") == "file") & full.may_match(F.col("x.unit"))))
    # a unit is named by what it holds, so rows that repeat an id stay apart
    of = F.xxhash64("d", "path", "u", "x.unit")
    # terms of a unit are counted in its row, so nothing is shuffled but one row of sums for each unit
    listed = units.select("d", "path", "x.kind", of.alias("unit"), F.array_sort(F.regexp_extract_all("x.unit", F.lit(TERM), F.lit(0))).alias("s")).where("size(s) > 0")
    listed = listed.withColumn("at", F.expr("filter(sequence(1, size(s)), i -> i = 1 OR s[i - 1] <> s[i - 2])"))
    counted = listed.select("d", "path", "kind", "unit", F.posexplode(F.expr("transform(at, (p, k) -> struct(s[p - 1] AS term, coalesce(get(at, k + 1), size(s) + 1) - p AS tf))")).alias("pos", "t"))
    # the table of terms grows with the templates alone; beyond a million entries it is shuffled
    terms_of = F.broadcast(by_term) if len(vectors) * len(names) <= 1_000_000 else by_term
    weighed = counted.select("d", "path", "kind", "unit", "pos", "t.term", "t.tf").join(terms_of, "term", "left").withColumn("x", F.col("tf") * F.coalesce("idf", F.lit(known.other)))
    sums = [F.sum(F.col("x") * F.get("w", F.lit(k))).alias(f"w{k}") for k in range(len(names))]
    # rows that come more than once add up to a multiple, which copies takes out again
    units = weighed.groupBy("unit").agg(*[F.first(c).alias(c) for c in ("d", "path", "kind")], F.count(F.when(F.col("pos") == 0, 1)).alias("copies"), F.sum(F.col("x") * F.col("x")).alias("square"), F.sum(F.when(~F.coalesce("stop", F.lit(False)), F.col("x") * F.col("x"))).alias("heavy"), *sums)
    cosine = [F.round(F.col(f"w{k}") / F.sqrt(F.col("copies") * F.col("square" if k < len(known.names) else "heavy")), 6) for k in range(len(names))]
    enough = [(c >= (threshold if k < len(known.names) else FULL)) & (F.lit(k < len(known.names)) | (F.col("kind") == "file")) for k, c in enumerate(cosine)]
    found = F.array_compact(F.array(*[F.when(e, F.struct(F.lit(n).alias("name"), c.alias("score"))) for e, n, c in zip(enough, names, cosine, strict=True)]))
    scored = scratch.write(units.select("d", "path", "kind", F.explode(found).alias("m")).select("d", "path", "kind", "m.name", "m.score"))
    # a licence file says more than a statement; then the better score, then the name
    ranked = F.struct((F.col("kind") == "file").cast("int").alias("f"), F.col("score").alias("s"), F.lit(0).alias("z"))
    best = scored.groupBy("d", "path", "kind", "name").agg(F.max("score").alias("score"))
    top = best.groupBy("d", "path").agg(F.max(ranked).alias("top"))
    stated = best.join(top, ["d", "path"]).where((F.col("score") == F.col("top.s")) & ((F.col("kind") == "file").cast("int") == F.col("top.f")))
    stated = scratch.write(stated.groupBy("d", "path", "kind", "score").agg(F.min("name").alias("license")))

    folder = F.regexp_replace("path", r"/[^/]*$", "")
    licensed = stated.where("kind = 'file'").groupBy(folder.alias("up")).agg(F.min(F.struct("path", "license", "score")).alias("of"))
    # ancestors of a directory, each with its depth: the directory itself, its parents, the root ""
    folders = own.select(folder.alias("folder")).distinct()
    above = folders.select("folder", F.explode(F.expr("transform(sequence(0, size(split(folder, '/')) - 1), i -> struct(i AS depth, array_join(slice(split(folder, '/'), 1, i + 1), '/') AS up))")).alias("a"))
    nearest = above.select("folder", "a.depth", "a.up").join(licensed, "up").groupBy("folder").agg(F.max(F.struct("depth", "of")).alias("near"))
    each = own.select("d", "path", folder.alias("folder")).distinct()
    joined = each.join(stated, ["d", "path"], "left").join(nearest.select("folder", "near.of"), "folder", "left")
    stands = F.col("license").isNotNull()
    return scratch.finish(joined.select(
        F.col("d").alias(id_col), "path",
        F.coalesce("license", "of.license").alias("license"),
        F.when(stands, F.col("kind")).when(F.col("of").isNotNull(), "inherited").otherwise("none").alias("basis"),
        F.coalesce("score", "of.score").alias("score"),
        F.when(stands, F.col("path")).otherwise(F.col("of.path")).alias("from_path"),
    ))


def document_files(documents: DataFrame) -> DataFrame:
    """``documents`` as files: /source/thousand/doc_id.txt."""
    path = F.concat(F.lit("/"), F.coalesce("source", F.lit("unknown")), F.lit("/"), F.floor(F.col("doc_id") / 1000).cast("string"), F.lit("/"), F.col("doc_id").cast("string"), F.lit(".txt"))
    return documents.select("doc_id", path.alias("path"), "text")


def oracle(threshold: float = 0.7) -> str:
    known = Weights(TEMPLATES, threshold)
    idf = ", ".join(f"('{t}', {w!r}::DOUBLE)" for t, w in known.idf.items())
    vectors = ", ".join(f"({k}, '{n}', '{t}', {w!r}::DOUBLE)" for k, n, t, w in known.vectors)
    return rf"""
WITH idf(term, idf) AS (VALUES {idf}), vec(template, name, term, w) AS (VALUES {vectors}),
f AS (SELECT doc_id, '/' || coalesce(source, 'unknown') || '/' || (doc_id // 1000) || '/' || doc_id || '.txt' AS path,
             lower(text) AS text FROM documents),
u AS (SELECT doc_id, path, 'statement' AS kind, unnest(string_split(text, chr(10))) AS unit FROM f
      UNION SELECT doc_id, path, 'statement', unnest(string_split_regex(text, '\n[ \t\r]*\n')) FROM f
      UNION SELECT doc_id, path, 'file', text FROM f),
n AS (SELECT *, row_number() OVER () AS k FROM u WHERE unit IS NOT NULL),
c AS (SELECT k, term, count(*) AS tf FROM (SELECT k, unnest(regexp_extract_all(unit, '{TERM}')) AS term FROM n) GROUP BY 1, 2),
x AS (SELECT c.*, idf.idf IS NOT NULL AS known, tf * coalesce(idf.idf, {known.other!r}::DOUBLE) AS x FROM c LEFT JOIN idf USING (term)),
norms AS (SELECT k, sqrt(sum(x * x)) AS norm FROM x GROUP BY 1),
dots AS (SELECT k, template, name, sum(x * w) AS dot FROM x JOIN vec USING (term) GROUP BY 1, 2, 3),
s AS (SELECT doc_id, path, kind, name, max(round(dot / norm, 6)) AS score FROM dots JOIN norms USING (k) JOIN n USING (k) GROUP BY 1, 2, 3, 4),
r AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY (kind = 'file') DESC, score DESC, name) AS q FROM s WHERE score >= {threshold}::DOUBLE),
st AS (SELECT doc_id, path, kind, name AS license, score FROM r WHERE q = 1),
lf AS (SELECT regexp_replace(path, '/[^/]*$', '') AS up, arg_min(license, path) AS license, arg_min(score, path) AS score, min(path) AS path FROM st WHERE kind = 'file' GROUP BY 1),
near AS (SELECT f.doc_id, lf.*, row_number() OVER (PARTITION BY f.doc_id ORDER BY length(lf.up) DESC) AS q FROM f JOIN lf
         ON regexp_replace(f.path, '/[^/]*$', '') = lf.up OR starts_with(f.path, lf.up || '/'))
SELECT f.doc_id, f.path, coalesce(st.license, near.license) AS license,
       CASE WHEN st.license IS NOT NULL THEN st.kind WHEN near.license IS NOT NULL THEN 'inherited' ELSE 'none' END AS basis,
       coalesce(st.score, near.score) AS score, CASE WHEN st.license IS NOT NULL THEN f.path ELSE near.path END AS from_path
FROM f LEFT JOIN st USING (doc_id) LEFT JOIN near ON near.doc_id = f.doc_id AND near.q = 1
"""
