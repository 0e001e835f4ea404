"""Licence scan in DataFrame functions alone: sparse TF-IDF cosine to templates, then inheritance along paths.

Units are the lines, sentences and paragraphs of a text that hold an anchor, and the whole text of a file with a licence's
usual name. Such a file, or one of a single line, is a licence file: its directory and all below inherit its licence, the
nearest ancestor first.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import cut, join_with_hot_keys

#: Usual notices and opening lines of public licences. The clause on redistribution, which the two BSD
#: licences share, stands for the longer one.
NOTICES = {
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.',
    ),
    "BSD-2-Clause": ("Released under the BSD 2-Clause License.", "Simplified BSD License."),
    "BSD-3-Clause": (
        "Redistribution and use under the BSD 3-Clause License.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    ),
    "CC-BY-4.0": ("Licensed under CC BY 4.0, Creative Commons Attribution.", "Creative Commons Attribution 4.0 International License."),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0.", "Creative Commons Attribution-ShareAlike 4.0 International License."),
    "CC0-1.0": ("Dedicated to the public domain under CC0 1.0 Universal.",),
    "ISC": ("Released under the ISC License.", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    "MIT": (
        "Released under the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, '
        "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    ),
    "MPL-2.0": ("Subject to the terms of the Mozilla Public License, v. 2.0.", "Mozilla Public License Version 2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
}
#: SPDX identifier, name, short name, version and date of the GNU licences.
GNU = (
    ("AGPL-3.0", "GNU Affero General Public License", "AGPL", "3", "19 November 2007"),
    ("GPL-2.0", "GNU General Public License", "GPL", "2", "June 1991"),
    ("GPL-3.0", "GNU General Public License", "GPL", "3", "29 June 2007"),
    ("LGPL-2.1", "GNU Lesser General Public License", "LGPL", "2.1", "February 1999"),
    ("LGPL-3.0", "GNU Lesser General Public License", "LGPL", "3", "29 June 2007"),
)


def gnu_notices(name: str, short: str, version: str, date: str) -> tuple[str, ...]:
    """Short notices, heading and file header of a GNU licence."""
    return (
        f"This work is licensed under the {name}, version {version}.",
        f"{name} Version {version}, {date}",
        f"This program is free software: you can redistribute it and/or modify it under the terms of the {name} as published by the Free Software Foundation, either version {version} of the License, or (at your option) any later version.",
        f"Licensed under the {short} version {version}.",
        f"Licensed under the {short}v{version}.",
        f"Licensed under the {name.replace('General Public License', 'GPL')} v{version}.",
    )


#: Notices by SPDX identifier.
TEMPLATES: dict[str, tuple[str, ...]] = NOTICES | {spdx: gnu_notices(*rest) for spdx, *rest in GNU}
#: A unit has one of these.
ANCHORS = ("licens", "licenc", "copyright", "spdx", "redistribution", "public domain", "is hereby granted", "gpl", "free software")
LICENSE_FILE = r"(?i)^(licen[sc]e|copying|notice|unlicense)(\.[a-z]+)?$"
#: A licence expression after the tag of the SPDX short form, in lower case.
SPDX_ID = r"\(*[a-z0-9.+\-]+\)*"
SPDX = rf"spdx-license-identifier:[ \t]*({SPDX_ID}(?:[ \t]+(?:and|or|with)[ \t]+{SPDX_ID})*)"
TERM = r"[^a-z0-9]+"
#: Blanks and the marks that begin lines of a comment.
MARGIN = r"[\x09-\x0D\x20*/#;%\-]"
PARAGRAPH_END = rf"\n{MARGIN}*\n"
SENTENCE_END = rf"([.;!?]){MARGIN}+([A-Z])"
MIN_COSINE = 0.5


def terms(text: str) -> list[str]:
    return [t for t in re.split(TERM, text.lower()) if t]


def weights(templates: Mapping[str, str | Sequence[str]]) -> tuple[dict[str, float], float, dict[tuple[str, int], dict[str, float]]]:
    """Inverse document frequencies over the notices, that of any other term, and the unit vectors by licence and number.

    They are of the templates alone, so that a text's result does not depend on its corpus.
    """
    notices = {k: (v,) if isinstance(v, str) else tuple(v) for k, v in templates.items()}
    bags = {(k, i): Counter(terms(text)) for k, texts in sorted(notices.items()) for i, text in enumerate(texts)}
    n = len(bags)
    df = Counter(t for bag in bags.values() for t in bag)
    idf = {t: math.log((1 + n) / (1 + d)) + 1 for t, d in sorted(df.items())}
    vectors = {}
    for k, bag in bags.items():
        norm = math.sqrt(sum((c * idf[t]) ** 2 for t, c in bag.items()))
        vectors[k] = {t: c * idf[t] / norm for t, c in bag.items()}
    return idf, math.log(1 + n) + 1, vectors


def _lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n"), lambda x: F.trim(F.regexp_replace(x, r"[\x09-\x0D]", " ")) != "")


def identifiers(low: Column) -> Column:
    """The identifiers that the SPDX tags of a lower-cased text name, without brackets and without -only, -or-later or +."""
    names = F.flatten(F.transform(F.regexp_extract_all(low, F.lit(SPDX), 1), lambda x: F.split(x, r"[ \t()]+")))
    return F.array_distinct(F.transform(names, lambda x: F.regexp_replace(x, r"(-only|-or-later|\+)?\.?$", "")))


def units(text: Column, is_license_file: Column) -> Column:
    """Lines, sentences and paragraphs with an anchor, and the whole text of a licence file, as terms between single spaces; each once."""
    paragraphs = F.split(text, PARAGRAPH_END)
    sentences = F.flatten(F.transform(paragraphs, lambda x: F.split(F.regexp_replace(x, SENTENCE_END, "$1\u0001$2"), "\u0001")))
    parts = F.filter(F.concat(F.split(text, "\n"), sentences, paragraphs), lambda x: _any_anchor(F.lower(x)))
    parts = F.concat(parts, F.when(is_license_file, F.array(text)).otherwise(F.array().cast("array<string>")))
    return F.array_distinct(F.transform(parts, lambda x: F.trim(F.regexp_replace(F.lower(x), TERM, " "))))


def header_matches(files: DataFrame, templates: Mapping[str, str | Sequence[str]] = TEMPLATES, min_cosine: float = MIN_COSINE) -> DataFrame:
    """Best template of every file (file_id, text, and name if there is one) that fits any: file_id, license, cosine, n_lines.

    Every unit is compared with every notice. An SPDX tag with a template's identifier fits it with cosine 1.
    Ties go to the template that comes first by name.
    """
    idf, other, vectors = weights(templates)
    spark = files.sparkSession
    entries = [(k, i, t, float(w)) for (k, i), vector in vectors.items() for t, w in vector.items()]
    sparse = spark.createDataFrame(entries, "license string, notice int, term string, template_weight double")
    known = spark.createDataFrame([(t, float(w)) for t, w in idf.items()], "term string, idf double")
    low = F.lower(F.col("text"))
    named = F.coalesce(F.col("name").rlike(LICENSE_FILE), F.lit(False)) if "name" in files.columns else F.lit(False)
    anchored = files.where((_any_anchor(low) | named) & F.col("text").isNotNull()).select(
        "file_id", units(F.col("text"), named).alias("units"), F.size(_lines(F.col("text"))).alias("n_lines"), low.contains("spdx-license-identifier:").alias("tagged"), identifiers(low).alias("identifiers")
    )
    # rows that repeat a file_id stay apart, else their terms would add up
    anchored = cut(anchored.withColumn("row_no", F.monotonically_increasing_id()))
    unit = ["file_id", "row_no", "n_lines", "unit_no"]
    found = anchored.select("file_id", "row_no", "n_lines", F.posexplode("units").alias("unit_no", "unit"))
    found = found.select(*unit, F.explode(F.split("unit", " ")).alias("term")).where("term <> ''")
    tf = found.groupBy(*unit, "term").agg(F.count("*").alias("tf"))
    tf = tf.join(F.broadcast(known), "term", "left").withColumn("weight", F.col("tf") * F.coalesce("idf", F.lit(other)))
    norms = tf.groupBy(*unit).agg(
        F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("norm"),
        F.collect_list(F.when(F.col("idf").isNotNull(), F.struct("term", "weight"))).alias("bag"),
    )
    pairs = norms.select(*unit, "norm", F.explode("bag").alias("cell")).select(*unit, "norm", "cell.term", "cell.weight")
    dots = pairs.join(F.broadcast(sparse), "term").groupBy(*unit, "license", "notice").agg((F.sum(F.col("weight") * F.col("template_weight")) / F.first("norm")).alias("cosine"))
    dots = dots.withColumn("cosine", F.round("cosine", 6)).where(F.col("cosine") >= min_cosine)
    by_id = spark.createDataFrame([(k.lower(), k) for k in sorted(templates)], "identifier string, license string")
    tagged = anchored.where("tagged").select("file_id", "n_lines", F.explode("identifiers").alias("identifier")).join(F.broadcast(by_id), "identifier")
    dots = dots.select("file_id", "n_lines", "license", "cosine").unionByName(tagged.select("file_id", "n_lines", "license", F.lit(1.0).alias("cosine")))
    best = dots.groupBy("file_id").agg(F.min(F.struct((-F.col("cosine")).alias("c"), "license", "n_lines")).alias("best"))
    return best.select("file_id", F.col("best.license").alias("license"), (-F.col("best.c")).alias("cosine"), F.col("best.n_lines").alias("n_lines"))


def _any_anchor(text: Column) -> Column:
    out = F.lit(False)
    for anchor in ANCHORS:
        out = out | text.contains(anchor)
    return out


def scan(docs: DataFrame, path: Column, id_col: str = "doc_id", text_col: str = "text", templates: Mapping[str, str | Sequence[str]] = TEMPLATES, min_cosine: float = MIN_COSINE) -> DataFrame:
    """doc_id, path, license, found_by (header, inherited, none), cosine and inherited_from of every row.

    A row's own units decide; else the nearest ancestor directory with a licence file, where of several files the one with
    the highest cosine, then the first by name, counts. A null path is the empty one, in the root. Null and empty texts have no header.
    Rows that repeat a doc_id share the best header of them all.
    """
    files = docs.select(F.col(id_col).alias("file_id"), F.coalesce(path, F.lit("")).alias("path"), F.col(text_col).alias("text"))
    n = files.count()
    files = files.withColumn("dir", F.regexp_replace("path", r"/?[^/]*$", "")).withColumn("name", F.regexp_extract("path", r"([^/]*)$", 1))
    found = cut(header_matches(files.select("file_id", "name", "text"), templates, min_cosine), n)
    names = files.select("file_id", "path", "dir", "name")
    own = names.join(found, "file_id", "left")
    givers = own.where(F.col("license").isNotNull() & ((F.col("n_lines") == 1) | F.col("name").rlike(LICENSE_FILE)))
    givers = givers.groupBy("dir").agg(F.min(F.struct((-F.col("cosine")).alias("c"), "name", "license")).alias("best"))
    givers = givers.select(F.col("dir").alias("giver"), F.col("best.license").alias("given"))
    dirs = cut(own.groupBy("dir").agg(F.count("*").alias("n_files")), n)
    parts = F.split("dir", "/")
    chain = F.transform(F.sequence(F.lit(0), F.size(parts)), lambda i: F.concat_ws("/", F.slice(parts, F.lit(1), i)))
    near = dirs.select("dir", F.explode(chain).alias("giver")).join(givers, "giver").groupBy("dir").agg(F.max(F.struct(F.length("giver").alias("depth"), "giver", "given")).alias("near"))
    dirs = dirs.join(near, "dir", "left").select("dir", "n_files", F.col("near.given").alias("given"), F.col("near.giver").alias("giver"))
    total = dirs.agg(F.coalesce(F.sum("n_files"), F.lit(0))).first()[0]
    out = join_with_hot_keys(own, dirs, ["dir"], "n_files", total)
    how = F.when(F.col("license").isNotNull(), "header").when(F.col("given").isNotNull(), "inherited").otherwise("none")
    return out.select(
        F.col("file_id").alias("doc_id"),
        "path",
        F.coalesce("license", "given").alias("license"),
        how.alias("found_by"),
        "cosine",
        F.when(how == "inherited", F.col("giver")).alias("inherited_from"),
    )
