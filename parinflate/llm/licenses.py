"""License scans, by DataFrame functions only.

Units of a file (its lines, their sentences and its paragraphs) are compared with licence templates by sparse TF-IDF cosine. A file
is licensed by its own header, or inherits from the nearest ancestor directory with a licence file, found by joining directory paths.
An SPDX tag names its licence itself and goes before templates; a reservation of all rights counts where no licence is granted.

Weights come from the files: how many hold a term. A template's heaviest terms, without which a unit cannot reach the threshold,
filter units first, without loss: the cosine is at most the norm of the template's terms that a unit shares.

Defined results: a null text or path has no licence; rows that repeat a path are one file with the units of all; equal cosines
go to the first licence by name; without rows there are none. Columns beyond id, path and text are not read.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.runtime import materialize, table

THRESHOLD = 0.6
#: Public licence notices.
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0'),
    ("MIT", "Released under the MIT License."),
    ("MIT", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction'),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("LGPL-3.0", "This library is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("LGPL-2.1", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("LGPL-3.0", "GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    ("LGPL-2.1", "GNU LESSER GENERAL PUBLIC LICENSE Version 2.1, February 1999"),
    ("GPL-3.0", "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    ("GPL-2.0", "GNU GENERAL PUBLIC LICENSE Version 2, June 1991"),
    ("Apache-2.0", "Apache License Version 2.0, January 2004"),
    ("All-Rights-Reserved", "All rights reserved."),
)
#: What a file has that grants nothing; any licence goes before it.
RESERVED = "All-Rights-Reserved"
SPDX = r"(?i)SPDX-License-Identifier:[ \t]*\(?([a-z0-9.+-]+(?: (?:OR|AND|WITH) [a-z0-9.+-]+)*)"
#: Common words, which vectors leave out.
COMMON = frozenset("a an and any are as at be by can for from if in is it may not of on or that the this to under was with without you your".split())
LICENCE_FILE = r"(?i)^(licen[cs]e|copying|unlicense)(\..*|-.*)?$"


def terms(text: str) -> list[str]:
    return [t for t in re.split(r"[^a-z0-9]+", text.lower()) if t and t not in COMMON]


class Templates:
    """Normalised term weights of each template and what filters units without loss."""

    def __init__(self, templates: tuple[tuple[str, str], ...] = TEMPLATES, threshold: float = THRESHOLD, held: dict[str, int] | None = None, files: int = 0):
        """``held`` says how many of ``files`` files hold a term; without it the templates themselves are counted."""
        self.threshold = threshold
        counts = [Counter(terms(t)) for _, t in templates]
        df = Counter(t for c in counts for t in c)
        self.files = len(counts) if held is None else files
        if held is not None:
            df = {t: held.get(t, 0) for t in df}
        self.idf = {t: math.log((1 + self.files) / (1 + n)) + 1 for t, n in df.items()}
        self.unseen = math.log(1 + self.files) + 1
        self.rows, first = [], set()
        for k, ((name, _), c) in enumerate(zip(templates, counts, strict=True)):
            w = {t: n * self.idf[t] for t, n in c.items()}
            norm = math.sqrt(sum(x * x for x in w.values()))
            self.rows += [(k, name, t, x / norm) for t, x in w.items()]
            # Terms that may be all a unit shares without reaching the threshold; it needs one of the others.
            spare = threshold**2 * 0.999
            for t in sorted(w, key=lambda t: (w[t], t)):
                spare -= (w[t] / norm) ** 2
                if spare <= 0:
                    first.add(t)
        self.first = sorted(first)
        #: Most that a term adds to the shared mass of any template.
        self.mass: dict[str, float] = {}
        for _, _, t, x in self.rows:
            self.mass[t] = max(self.mass.get(t, 0.0), x * x)


def units(text: Column, templates: Templates) -> Column:
    """Lines, their sentences, and paragraphs of more than one line, whose terms can reach the threshold: the cosine is at most the root of the shared mass."""
    paragraphs = F.filter(F.split(text, r"\n[ \t\r]*\n"), lambda p: p.contains("\n"))
    vocabulary = F.lit(list(templates.mass))
    mass = F.create_map(*[F.lit(x) for pair in templates.mass.items() for x in pair])
    least = templates.threshold**2 * 0.999

    def reaches(u: Column) -> Column:
        shared = F.array_intersect(F.split(F.lower(u), "[^a-z0-9]+"), vocabulary)
        return F.aggregate(shared, F.lit(0.0), lambda a, t: a + F.coalesce(F.element_at(mass, t), F.lit(0.0))) >= least

    lines = F.filter(F.split(text, "\n"), lambda u: holds(u, templates.first))
    sentences = F.filter(F.flatten(F.transform(lines, lambda u: F.split(u, r"(?<=[.!?;])[ \t]+"))), lambda u: holds(u, templates.first))
    return F.array_distinct(F.filter(F.concat(lines, sentences, F.filter(paragraphs, lambda u: holds(u, templates.first))), reaches))


def holds(text: Column, first: list[str]) -> Column:
    return F.arrays_overlap(F.split(F.lower(text), "[^a-z0-9]+"), F.lit(first))


def frequencies(files: DataFrame) -> DataFrame:
    """(term, df): how many rows of ``files`` hold each term."""
    words = files.where(F.col("path").isNotNull()).select(F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-z0-9]+"))).alias("term"))
    return words.where("term <> ''").groupBy("term").agg(F.count(F.lit(1)).alias("df"))


def rank(license_: Column) -> Column:
    """Licences before reservations."""
    return (license_ == RESERVED).cast("int")


def matches(files: DataFrame, templates: Templates, held: DataFrame | None = None) -> DataFrame:
    """(path, license, cosine): the best licence of each file that has one; ``files`` has path and text, ``held`` frequencies of terms."""
    spark = files.sparkSession
    if held is None:
        known = F.broadcast(spark.createDataFrame([(t, w) for t, w in templates.idf.items()], "term string, idf double"))
    else:
        known = held.select("term", (F.log(F.lit(1.0 + templates.files) / (F.col("df") + 1)) + 1).alias("idf"))
    weights = F.broadcast(spark.createDataFrame(templates.rows, "template int, license string, term string, weight double"))
    found = files.where(F.col("path").isNotNull() & holds(F.col("text"), templates.first)).select("path", F.explode(units(F.col("text"), templates)).alias("words"))
    # From here a unit is its digest and its terms; its text does not move.
    found = found.select("path", F.unhex(F.md5("words")).alias("unit"), F.array_remove(F.split(F.lower("words"), "[^a-z0-9]+"), "").alias("terms")).dropDuplicates(["path", "unit"])
    found = found.select("path", "unit", F.explode("terms").alias("term")).where(~F.col("term").isin(*sorted(COMMON)))
    tf = found.groupBy("path", "unit", "term").agg(F.count(F.lit(1)).alias("tf")).join(known, "term", "left")
    tf = tf.select("path", "unit", "term", (F.col("tf") * F.coalesce("idf", F.lit(templates.unseen))).alias("w"))
    norm = tf.groupBy("path", "unit").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dot = tf.join(weights, "term").groupBy("path", "unit", "template", "license").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"))
    cos = dot.join(norm, ["path", "unit"]).select("path", "license", F.round(F.col("dot") / F.col("norm"), 6).alias("cosine")).where(F.col("cosine") >= templates.threshold)
    tags = files.where(F.col("path").isNotNull() & F.lower("text").contains("spdx-license-identifier:")).select("path", F.explode(F.regexp_extract_all("text", F.lit(SPDX), F.lit(1))).alias("tag"))
    # Tags say more of the version than templates do; names are those of the templates.
    tags = tags.select("path", F.regexp_replace("tag", r"(?i)(-only|-or-later|\+)(?= |$)", "").alias("license"), F.lit(1.0).alias("cosine"), F.lit(-1).alias("rank"))
    cos = cos.select("path", "license", "cosine", rank(F.col("license")).alias("rank")).union(tags)
    best = cos.groupBy("path").agg(F.min(F.struct("rank", (-F.col("cosine")).alias("less"), "license")).alias("x"))
    return best.select("path", "x.license", (-F.col("x.less")).alias("cosine"))


def ancestors(directory: Column) -> Column:
    """The directory and all above it, as structs of depth and path; the root is ''."""
    parts = F.split(directory, "/")
    return F.transform(F.sequence(F.lit(1), F.size(parts)), lambda n: F.struct(n.alias("depth"), F.array_join(F.slice(parts, F.lit(1), n), "/").alias("dir")))


def directory(path: Column) -> Column:
    return F.when(path.contains("/"), F.regexp_replace(path, "/[^/]*$", "")).otherwise(F.lit(""))


def scan(files: DataFrame, templates: Templates | None = None) -> DataFrame:
    """(path, license, how, cosine, from_dir) of every path: how is header, file, inherited or none."""
    held = None
    if templates is None:
        held = materialize(frequencies(files), "frequencies")
        n = files.where("path IS NOT NULL AND text IS NOT NULL").count()
        vocabulary = sorted(Templates().idf)
        templates = Templates(held={r.term: r.df for r in held.where(F.col("term").isin(vocabulary)).collect()}, files=n)
    thin = files.select("path").where("path IS NOT NULL").distinct().select("path", directory(F.col("path")).alias("dir"), F.regexp_extract("path", "[^/]*$", 0).rlike(LICENCE_FILE).alias("is_file"))
    own = materialize(matches(files, templates, held), "licenses")
    placed = materialize(thin.join(own, "path", "left"), "placed")
    # Written, as is what comes of it, so that joins shuffle both sides and AQE can split a directory that many others look up or lie in.
    granted = placed.where("is_file AND license IS NOT NULL").groupBy(F.col("dir").alias("g_dir")).agg(F.min(F.struct(rank(F.col("license")), (-F.col("cosine")).alias("less"), "license")).alias("x")).select("g_dir", F.col("x.license").alias("g_license"))
    granted = materialize(granted, "granted")
    # Directories, not files, look up: a full directory is one row.
    above = placed.select("dir").distinct().withColumn("up", F.explode(ancestors(F.col("dir"))))
    nearest = above.join(granted, F.col("up.dir") == F.col("g_dir")).groupBy(F.col("dir").alias("n_dir")).agg(F.max(F.struct(F.col("up.depth").alias("depth"), "g_dir", "g_license")).alias("x")).select("n_dir", F.col("x.g_dir").alias("from_dir"), F.col("x.g_license").alias("inherited"))
    out = placed.join(materialize(nearest, "nearest"), F.col("dir") == F.col("n_dir"), "left")
    how = F.when(F.col("license").isNotNull(), F.when(F.col("is_file"), "file").otherwise("header")).when(F.col("inherited").isNotNull(), "inherited").otherwise("none")
    return out.select("path", F.coalesce("license", "inherited").alias("license"), how.alias("how"), "cosine", F.when(F.col("license").isNull(), F.col("from_dir")).alias("from_dir"))


def document_path(id_: Column, source: Column, text: Column) -> Column:
    """A path for each document: sources are trees of a directory for each thousand ids and in it one for each two hundred.

    A hash of the id makes one row in ten a licence file, three of four in the lower directory and one in the upper. A row without
    id lies in its source's root under a name from its text, so only rows of equal text share a file.
    """
    root = F.concat(F.coalesce(source, F.lit("none")), F.lit("/"))
    high, mid = F.floor(id_ / 1000).cast("string"), F.floor(F.pmod(id_, F.lit(1000)) / 200).cast("string")
    upper, draw, name = F.concat(root, high, F.lit("/")), F.pmod(F.xxhash64(id_), F.lit(40)), id_.cast("string")
    lower = F.concat(upper, mid, F.lit("/"))
    path = F.when(draw == 0, F.concat(upper, F.lit("LICENSE-"), name)).when(draw < 4, F.concat(lower, F.lit("LICENSE-"), name))
    unnamed = F.concat(root, F.lit("unnamed-"), F.md5(F.coalesce(text, F.lit(""))), F.lit(".txt"))
    return F.when(id_.isNull(), unnamed).otherwise(path.otherwise(F.concat(lower, F.lit("d"), name, F.lit(".txt"))))


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", document_path(F.col("doc_id"), F.col("source"), F.col("text")).alias("path"), "text")
    found = scan(docs.select("path", "text"))
    return docs.select("doc_id", F.col("path").alias("d_path")).join(found, F.col("d_path") == F.col("path"), "left").select("doc_id", F.col("d_path").alias("path"), "license", "how", "cosine", "from_dir")
