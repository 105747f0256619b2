"""Licence scan: sparse TF-IDF cosine to templates, then inheritance from the nearest directory.

Templates are usual notices and whole licence texts (``licence_texts``, their ``TERMS`` weightiest terms). Units of a file are its whole
text, every line, and every block of two or more adjacent lines (but the whole); lines and blocks that deny a licence
(``DENIED``) are left out. A unit's vector has (1 + ln tf) * idf for each of its terms, with document
frequencies counted over all files; terms that no template has get the largest idf. The cosine to each
template comes from a join of the unit's terms with the templates' (a fixed, small table). A file whose
best line or block reaches ``MIN_HEADER`` has that licence by its header; a file whose whole text
reaches ``MIN_FILE`` is a licence file, which states the licence of its directory. A file near a whole
licence text has that licence; else the higher score of header and file is its own. Files without a licence of their own take that of the nearest ancestor directory that has a
licence file: directories are reduced to distinct ones, joined with their ancestors, and the deepest
match is joined back.

Only built-in functions. Only units that can reach a cut are exploded into terms: they have a telling
term (``telling_terms``) and enough of their own length on template terms (``reach``). Both tests are
bounds, so nothing is missed. Document
frequencies are partial counts of some thousand terms; a directory that holds a third of all files
is one row of the directory table, which its files get without a shuffle (``common.join_hot``).

Edge cases: a null or empty text has no licence of its own; a null source or language is a directory
named ``null``; ties go to the higher score, then the smaller licence name, and from file to header; in a
directory with several licence files to the higher score, then the smaller path; repeated rows get equal
results, and rows with one path and several texts are parts of one file; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

import json
import math
import re
from collections import Counter
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import common as C

MIN_HEADER, MIN_FILE = 0.55, 0.4
DENIED = "(not|never|no longer) ([a-z]+ ){0,2}(licen[sc]ed|released|available|distributed) (under|by|on)"
LINES, BLOCKS = "[\\r\\n]+", "\\r?\\n[ \\t#*/;-]*\\r?\\n"
#: Terms kept of a template of over LONG words.
TERMS, LONG = 96, 100
#: Places of the table of template terms, and the largest (1 + ln x)^2 / x.
PLACES, STEEP = 1024, 4 / math.e
TERM = "[a-z0-9]+(?:[.][0-9]+)*"

# Usual wordings of licence notices.
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "This software is released under the terms of the MIT license. SPDX-License-Identifier: MIT"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This library is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Released under the BSD 3-Clause License. Redistribution and use in source and binary forms, with or without modification, are permitted"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License. Licensed under CC BY 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0. Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has dedicated this work to the public domain under CC0 1.0 Universal."),
    ("Proprietary", "Copyright. All rights reserved. No part may be reproduced without permission."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. SPDX-License-Identifier: ISC"),
    ("ISC", "Licensed under the ISC License."),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: The origin of this software must not be misrepresented; you must not claim that you wrote the original software. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. This notice may not be removed or altered from any source distribution."),
    ("BSD-3-Clause", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("LGPL-2.1", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("AGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
)
# The text that follows the MIT notice, and the section that sets the Affero licence apart.
MIT_REST = "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
AFFERO = "Remote Network Interaction; if you modify the Program, your modified version must prominently offer all users interacting with it remotely through a computer network an opportunity to receive the Corresponding Source of your version by providing access to the Corresponding Source from a network server at no charge, through some standard or customary means of facilitating copying of software."
#: Whole licence texts by file of ``licence_texts``.
WHOLE = {"Apache-2.0": "Apache-2.0", "GPL-2.0": "GPL-2", "GPL-3.0": "GPL-3", "LGPL-2.1": "LGPL-2.1", "LGPL-3.0": "LGPL-3", "MPL-2.0": "MPL-2.0", "CC0-1.0": "CC0-1.0", "BSD-3-Clause": "BSD", "Artistic-1.0": "Artistic"}


def templates() -> list[tuple[str, str]]:
    """(licence, text) of all templates: notices, then whole texts."""
    whole = [(name, (Path(__file__).parent / "licence_texts" / f"{file}.txt").read_text(encoding="utf-8")) for name, file in WHOLE.items()]
    affero = dict(whole)["GPL-3.0"].replace("GNU General Public License", "GNU Affero General Public License").replace("GNU GENERAL", "GNU AFFERO GENERAL")
    mit = next(text for name, text in TEMPLATES if name == "MIT" and text.startswith("Permission"))
    return [*TEMPLATES, *whole, ("AGPL-3.0", f"{affero} {AFFERO}"), ("MIT", f"MIT License Copyright {mit}, {MIT_REST}")]


def terms(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TERM), F.lit(0))


def term_table() -> list[tuple[int, str, str, int]]:
    """(template, licence, term, tf): notices with all their terms, whole texts with their ``TERMS`` weightiest among whole texts."""
    counts = [(i, name, Counter(re.findall(TERM, text.lower()))) for i, (name, text) in enumerate(templates())]
    whole = [c for i, _, c in counts if sum(c.values()) > LONG]
    spread = Counter(t for c in whole for t in c)
    out = []
    for i, name, c in counts:
        weight = {t: (1 + math.log(n)) * (1 + math.log((1 + len(whole)) / spread[t])) for t, n in c.items()} if sum(c.values()) > LONG else c
        out += [(i, name, t, c[t]) for t in sorted(weight, key=lambda t: (-weight[t], t))[: TERMS if weight is not c else None]]
    return out


def long_templates() -> list[int]:
    """Numbers of the whole licence texts among the templates."""
    return [i for i, (_, text) in enumerate(templates()) if len(re.findall(TERM, text.lower())) > LONG]


def template_terms(spark: SparkSession) -> DataFrame:
    """(template, licence, term, tf) of the fixed templates."""
    return spark.createDataFrame(term_table(), "template int, licence string, term string, tf int")


def scan(files: DataFrame, path: str = "path", text: str = "text") -> DataFrame:
    """(path, licence, how, score, stated_in): how is header, file, directory or null; stated_in the file that states it."""
    spark = files.sparkSession
    named = files.select(F.col(path).alias("path"), F.col(text).cast("string").alias("text"))
    known = C.materialize(template_terms(spark), "templates")
    vocabulary = known.select("term").distinct()

    # Document frequencies of the templates' terms over all files.
    wanted = F.lit([r["term"] for r in vocabulary.orderBy("term").collect()])
    sizes = named.select(F.explode_outer(F.concat(F.array(F.lit("")), F.array_intersect(F.coalesce(terms(F.col("text")), F.array().cast("array<string>")), wanted))).alias("term")).groupBy("term").agg(F.count("*").alias("df"))
    sizes = C.materialize(sizes, "term-counts")
    total = sizes.filter("term = ''").agg(F.coalesce(F.max("df"), F.lit(0))).first()[0]
    rare = F.log(F.lit(total + 1.0)) + 1.0
    idf = vocabulary.join(F.broadcast(sizes), "term", "left").select("term", (F.log(F.lit(total + 1.0) / (F.coalesce("df", F.lit(0)) + 1.0)) + 1.0).alias("idf"))
    idf = C.materialize(idf, "idf")
    weight = (F.log(F.col("tf").cast("double")) + 1.0)
    raw = known.join(F.broadcast(idf), "term").withColumn("w", weight * F.col("idf"))
    of_template = W.partitionBy("template")
    weights = raw.select("template", "licence", "term", (F.col("w") / F.sqrt(F.sum(F.col("w") * F.col("w")).over(of_template))).alias("w"))

    weights = C.materialize(weights, "template-weights")
    place = F.pmod(F.xxhash64("term"), F.lit(PLACES)).cast("int")
    known_rows = [tuple(r) for r in weights.join(F.broadcast(idf), "term").select("template", "term", "w", "idf", place).collect()]  # the fixed templates
    telling, can = F.lit(telling_terms([r[:4] for r in known_rows])), reach(known_rows, math.log(total + 1.0) + 1.0)
    tells = lambda x: F.arrays_overlap(terms(x), telling)
    kept = lambda x: can(x, MIN_HEADER) & ~F.lower(x).rlike(DENIED)
    blocks = F.filter(F.split("text", BLOCKS), lambda x: (x != F.col("text")) & x.rlike("[\\r\\n]"))
    lines = F.filter(F.array_distinct(F.concat(F.split("text", LINES), blocks)), kept)
    # Outer, and not filtered before: a filter on the array would have it made twice.
    every = F.concat(F.array(F.when(can(F.col("text"), MIN_FILE), F.col("text"))), lines)
    units = named.filter(tells(F.col("text"))).select("path", F.posexplode_outer(every).alias("unit", "words"))
    units = units.filter("words is not null").dropDuplicates(["path", "unit", "words"])
    counts = units.select("path", "unit", F.explode_outer(terms(F.col("words"))).alias("term")).filter("term is not null").groupBy("path", "unit", "term").agg(F.count("*").alias("tf"))
    counts = counts.join(F.broadcast(idf), "term", "left").withColumn("v", weight * F.coalesce(F.col("idf"), rare))
    norms = counts.groupBy("path", "unit").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    dots = counts.join(F.broadcast(weights), "term").groupBy("path", "unit", "template", "licence").agg(F.sum(F.col("v") * F.col("w")).alias("dot"))
    cosines = dots.join(norms, ["path", "unit"]).select("path", "unit", "template", "licence", F.round(F.col("dot") / F.col("norm"), 4).alias("score"))
    own = cosines.groupBy("path").agg(
        F.max(F.when((F.col("unit") > 0) & (F.col("score") >= MIN_HEADER), F.struct("score", F.translate("licence", _FORWARD, _BACKWARD).alias("order"), "licence"))).alias("header"),
        F.max(F.when((F.col("unit") == 0) & (F.col("score") >= MIN_FILE), F.struct("score", F.translate("licence", _FORWARD, _BACKWARD).alias("order"), "licence"))).alias("file"),
        F.max(F.when((F.col("unit") == 0) & F.col("template").isin(long_templates()) & (F.col("score") >= MIN_FILE), F.struct("score", F.translate("licence", _FORWARD, _BACKWARD).alias("order"), "licence"))).alias("whole"),
    )
    # Lines of a whole licence text quote notices of other licences: what the whole text is like counts first.
    own = own.withColumn("file", F.coalesce("whole", "file"))
    own = C.materialize(own.filter("header is not null or file is not null"), "own-licences")

    folder = lambda c: F.regexp_extract(c, "^(.*)/[^/]*$", 1)
    stated = own.filter("file is not null").select(folder(F.col("path")).alias("at"), "path", F.col("file.licence").alias("licence"), F.col("file.score").alias("score"))
    first = F.row_number().over(W.partitionBy("at").orderBy(F.desc("score"), "path"))
    stated = stated.withColumn("_r", first).filter("_r = 1").drop("_r")
    files_of = named.select("path", folder(F.col("path")).alias("folder"))
    files_of = C.materialize(files_of, "paths")
    folders = files_of.groupBy("folder").agg(F.count("*").alias("_n"))
    parts = F.split("folder", "/")
    ancestors = folders.select("folder", F.explode(F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.struct(i.alias("depth"), F.array_join(F.slice(parts, 1, i), "/").alias("at")))).alias("a")).select("folder", "a.depth", "a.at")
    nearest = ancestors.join(stated, "at").groupBy("folder").agg(F.max_by(F.struct("licence", "score", "path"), "depth").alias("near"))
    nearest = C.materialize(folders.join(nearest, "folder", "left"), "directory-licences")

    joined = C.join_hot(files_of, nearest, "folder", files_of.count()).join(own, "path", "left")
    by_file = F.col("file").isNotNull() & (F.col("whole").isNotNull() | F.col("header").isNull() | (F.col("file.score") > F.col("header.score")))
    joined = joined.withColumn("mine", F.when(by_file, F.col("file")).otherwise(F.col("header")))
    how = F.when(by_file, "file").when(F.col("header").isNotNull(), "header").when(F.col("near").isNotNull(), "directory")
    return joined.select(
        "path",
        F.coalesce("mine.licence", "near.licence").alias("licence"),
        how.alias("how"),
        F.coalesce("mine.score", "near.score").alias("score"),
        F.when(F.col("mine").isNotNull(), F.col("path")).otherwise(F.col("near.path")).alias("stated_in"),
    )


def reach(rows: list[tuple], rare: float):
    """A test of whether a unit's cosine to any template can reach a cut, made inside the row.

    By the inequality of Cauchy and Schwarz it is at most the share of the unit's length that lies on
    template terms; with (1 + ln tf)^2 <= STEEP tf that part is at most STEEP times a sum over occurrences.
    ``rows``: (template, term, w, idf, place) of the fixed templates; terms are found by their place.
    """
    table: list[list] = [[] for _ in range(PLACES)]
    for term, idf, at in sorted({(r[1], r[3], r[4]) for r in rows}):
        table[at].append({"t": term, "s": idf * idf})
    found = F.from_json(F.lit(json.dumps(table)), F.lit("array<array<struct<t:string,s:double>>>"))  # folded to one literal
    nothing = F.lit(0.0)

    def square(w: Column) -> Column:
        own = F.get(found, F.pmod(F.xxhash64(w), F.lit(PLACES)).cast("int"))
        return F.aggregate(own, nothing, lambda acc, e: F.when(e["t"] == w, e["s"]).otherwise(acc))

    def can(unit: Column, least: float) -> Column:
        def test(t: Column) -> Column:
            known = F.aggregate(t, nothing, lambda acc, w: acc + square(w))
            length = F.aggregate(F.array_distinct(t), nothing, lambda acc, w: acc + C.once(square(w), lambda x: F.when(x > 0, x).otherwise(rare * rare)))
            return F.lit(STEEP) * known >= F.lit(0.98 * least * least) * length

        return C.once(terms(unit), test)

    return can


def telling_terms(rows: list[tuple]) -> list[str]:
    """Terms of which a unit needs at least one to reach a cut: all but the commonest, on which no template has MIN_FILE of its length.

    ``rows``: (template, term, w, idf) of the fixed templates.
    """
    idf = {term: x for _, term, _, x in rows}
    own: dict[str, list] = {}
    for template, term, w, _ in rows:
        own.setdefault(term, []).append((template, w))
    mass: dict[int, float] = {}
    order = sorted(idf, key=lambda t: (idf[t], t))
    for k, term in enumerate(order):
        for template, w in own[term]:
            mass[template] = mass.get(template, 0.0) + w * w
            if mass[template] >= (0.99 * MIN_FILE) ** 2:
                return order[k:]
    return []


#: Code points of licence names turned around, so that the largest struct has the smallest name.
_FORWARD = "".join(map(chr, range(45, 123)))
_BACKWARD = _FORWARD[::-1]


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licence of every document, taken as the file /source/lang/doc_id."""
    docs = C.table(spark, sf_dir, "documents")
    part = lambda c: F.coalesce(F.regexp_replace(F.col(c), "/", "_"), F.lit("null"))
    files = docs.select(F.concat(F.lit("/"), part("source"), F.lit("/"), part("lang"), F.lit("/"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))).alias("path"), "text")
    found = scan(files)
    number = lambda c: F.regexp_extract(c, "/([0-9-]+)$", 1)
    as_id = lambda c: F.when(number(F.col(c)) != "", number(F.col(c))).cast("long")
    return found.select(as_id("path").alias("doc_id"), "path", "licence", "how", "score", as_id("stated_in").alias("stated_in"))


def oracle() -> str:
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    values = ", ".join(f"({i}, {quote(name)}, {quote(term)}, {tf})" for i, name, term, tf in term_table())
    tok = lambda c: f"regexp_extract_all(lower({c}), '{TERM}')"
    long = ", ".join(map(str, long_templates()))
    return f"""
    with f as (select '/' || coalesce(replace(source, '/', '_'), 'null') || '/' || coalesce(replace(lang, '/', '_'), 'null') as folder, doc_id, coalesce(text, '') as text from documents),
    p as (select *, folder || '/' || doc_id as path from f),
    t as (select * from (values {values}) v(template, licence, term, tf)),
    voc as (select distinct term from t),
    dfs as (select term, count(*) df from (select distinct path, term from (select path, unnest({tok('text')}) term from p)) semi join voc using (term) group by term),
    nn as (select count(*) n from p),
    idf as (select term, ln((n + 1.0) / (coalesce(df, 0) + 1.0)) + 1.0 idf from voc left join dfs using (term), nn),
    tw0 as (select template, licence, term, (ln(tf) + 1.0) * idf w from t join idf using (term)),
    tw as (select template, licence, term, w / sqrt(sum(w * w) over (partition by template)) w from tw0),
    units as (select path, 0 unit, text words from p union all
      select path, row_number() over (partition by path) unit, words from (select distinct path, unnest(list_concat(regexp_split_to_array(text, '{LINES}'), list_filter(regexp_split_to_array(text, '{BLOCKS}'), lambda x: x <> text and regexp_matches(x, '[\\r\\n]')))) words from p) where not regexp_matches(lower(words), '{DENIED}')),
    c0 as (select path, unit, term, count(*) tf from (select path, unit, unnest({tok('words')}) term from units) group by all),
    c as (select path, unit, term, (ln(tf) + 1.0) * coalesce(idf, ln(n + 1.0) + 1.0) v from c0 left join idf using (term), nn),
    norms as (select path, unit, sqrt(sum(v * v)) norm from c group by all),
    dots as (select path, unit, template, licence, sum(v * w) dot from c join tw using (term) group by all),
    cosines as (select path, unit, template, licence, round(dot / norm, 4) score from dots join norms using (path, unit)),
    own0 as (select path, min_by(licence, (-score, licence)) filter (unit > 0 and score >= {MIN_HEADER}) hl, max(score) filter (unit > 0 and score >= {MIN_HEADER}) hs,
      min_by(licence, (-score, licence)) filter (unit = 0 and score >= {MIN_FILE}) fl, max(score) filter (unit = 0 and score >= {MIN_FILE}) fs,
      min_by(licence, (-score, licence)) filter (unit = 0 and score >= {MIN_FILE} and template in ({long})) wl, max(score) filter (unit = 0 and score >= {MIN_FILE} and template in ({long})) ws from cosines group by path),
    own as (select path, hl, hs, coalesce(wl, fl) fl, coalesce(ws, fs) fs, wl from own0),
    stated as (select folder, path, doc_id, fl licence, fs score from own join p using (path) where fl is not null qualify row_number() over (partition by folder order by fs desc, path) = 1),
    mine as (select *, fl is not null and (wl is not null or hl is null or fs > hs) by_file from own)
    select p.doc_id, p.path, coalesce(case when by_file then fl else hl end, s.licence) licence,
      case when by_file then 'file' when hl is not null then 'header' when s.licence is not null then 'directory' end how,
      case when by_file then fs when hl is not null then hs else s.score end score,
      case when hl is not null or fl is not null then p.doc_id else s.doc_id end stated_in
    from p left join mine using (path) left join stated s on s.folder = p.folder"""
