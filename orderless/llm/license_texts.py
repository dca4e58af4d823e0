"""License scans over vectors of whole texts, header blocks, paragraphs and lines; then inheritance from licence files.

All in built-in functions. A text that holds a trigger word gives vectors of four kinds: the whole text, its header block (the
leading lines that are comments or blank), its paragraphs and its lines, the last two where they hold a trigger word
themselves. Templates are the full licence texts of the folder `licence_texts`, the paragraphs of the short ones, and common
notices. Every term of a candidate is weighted by 1 + ln((1 + FLOOR) / (share of all documents that hold it + FLOOR)): only
shares enter, so a cosine stays the same at every corpus size. A text whose whole vector is near a template is a licence
file and speaks for its directory; a document without a notice of its own takes the licence of its nearest ancestor directory.

Defined results: null or empty texts have no notice and may inherit. A whole text or header block that reaches FILE_LEAST counts before
paragraphs and lines, which licences share; else the most similar. Of equal similarities the larger kind counts, then the earlier
place, then the first template; of several licence files in a directory the most similar, then the least id. Rows with
equal ids are told apart. Broadcast are the templates alone, a fixed table.
"""

from __future__ import annotations

import functools
import pathlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, licenses
from .licenses import TRIGGER, directories, inherited, terms

# fixed values: notices beside those of the line scan; texts of the licences stand in the folder
NOTICES = (
    *licenses.TEMPLATES,
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("proprietary", "Copyright (c) All rights reserved."),
)
#: Short texts whose granting paragraph, which names them by itself, is a template too, since it is used as a notice in files.
SHORT = ("BSD-3-Clause", "ISC", "MIT")
GRANT = "hereby granted|redistribution and use"
FLOOR, LEAST, FILE_LEAST = 0.01, 0.5, 0.7
_BLANK = r"^[ \t\r]*(?:#+|//+|/?\*+/?|--+|;+|%+|<!--|-->)?[ \t\r]*\z"
_COMMENT = r"^[ \t\r]*(?:#|//|/?\*|--|;|%|<!--|\z)"
KINDS = ("file", "head", "paragraph", "line")


@functools.cache
def templates() -> tuple[tuple[str, str], ...]:
    """License and words of every template."""
    import re

    whole = [(p.stem, p.read_text()) for p in sorted((pathlib.Path(__file__).parent / "licence_texts").glob("*.txt"))]
    some = [(n, s) for n, t in whole if n in SHORT for s in re.split(r"\n\s*\n", t) if re.search(GRANT, s.lower())]
    return (*whole, *some, *NOTICES)


def shares(texts: DataFrame) -> DataFrame:
    """term and df, the number of texts that hold it, of every term."""
    return texts.select(F.explode(F.array_distinct(terms(F.col("text")))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("df"))


def candidates(texts: DataFrame) -> DataFrame:
    """uid, kind, place, words: each text with a trigger word whole, its header block, and paragraphs and lines with one."""
    held = texts.filter(F.lower("text").rlike(TRIGGER)).withColumn("lines", F.split("text", "\n", -1))
    comment = F.transform("lines", lambda x: x.rlike(_COMMENT))
    ends = F.array_position(comment, False)
    head = F.array_join(F.slice("lines", F.lit(1), F.when(ends > 0, (ends - 1).cast("int")).otherwise(F.size("lines"))), "\n")
    flat = F.array_join(F.transform("lines", lambda x: F.when(x.rlike(_BLANK), F.lit("")).otherwise(x)), "\n")
    piece = lambda kind, words: F.transform(words, lambda w, i: F.struct(F.lit(kind).alias("kind"), i.alias("place"), w.alias("words")))
    every = F.concat(piece(0, F.array("text")), piece(1, F.array(head)), piece(2, F.split(flat, "\n\n", -1)), piece(3, F.col("lines")))
    return held.select("uid", F.inline(every)).filter(F.lower("words").rlike(TRIGGER))


def notices(texts: DataFrame) -> DataFrame:
    """uid, kind, place, license, similarity of each candidate's best template; texts: uid, text."""
    spark = texts.sparkSession
    df = common.stage(shares(texts), "license-df")
    total = F.broadcast(texts.agg(F.count(F.lit(1)).alias("n")))
    weight = 1 + F.log((1 + FLOOR) / (F.coalesce("df", F.lit(0)) / F.col("n") + FLOOR))
    each = [F.struct(F.lit(i).alias("t"), F.lit(n).alias("license"), F.lit(t).alias("words")) for i, (n, t) in enumerate(templates())]
    template = spark.range(1).select(F.inline(F.array(*each))).select("t", "license", F.explode(terms(F.col("words"))).alias("term"))
    template = template.groupBy("t", "license", "term").agg(F.count(F.lit(1)).alias("tf")).join(df, "term", "left").crossJoin(total).withColumn("tw", F.col("tf") * weight)
    template = common.stage(template.select("t", "license", "term", "tw"), "license-templates")  # a fixed number of rows
    length = template.groupBy("t").agg(F.sqrt(F.sum(F.col("tw") * F.col("tw"))).alias("tn"))
    template = template.join(F.broadcast(length), "t").select("t", "license", "term", (F.col("tw") / F.col("tn")).alias("tw"))
    counted = candidates(texts).select("uid", "kind", "place", F.explode(terms(F.col("words"))).alias("term")).groupBy("uid", "kind", "place", "term").agg(F.count(F.lit(1)).alias("tf"))
    counted = counted.join(df.hint("merge"), "term").crossJoin(total).withColumn("w", F.col("tf") * weight)
    counted = common.stage(counted.select("uid", "kind", "place", "term", "w"), "license-terms")
    common.unstage(df)
    norm = counted.groupBy("uid", "kind", "place").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = counted.join(F.broadcast(template), "term").groupBy("uid", "kind", "place", "t", "license").agg(F.sum(F.col("w") * F.col("tw")).alias("dot"))
    near = dots.join(norm.hint("merge"), ["uid", "kind", "place"]).withColumn("similarity", F.round(F.col("dot") / F.col("norm"), 6))
    best = F.max(F.struct("similarity", (-F.col("t")).alias("t"), "license")).alias("best")
    return near.groupBy("uid", "kind", "place").agg(best).select("uid", "kind", "place", "best.license", "best.similarity")


def license_scan(docs: DataFrame, path: Column, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Per row: doc_id, path, license, similarity, part (kind of the vector that matched), origin (notice, inherited or none), licence_dir."""
    rows = docs.select(common.col(key).cast("long").alias("doc_id"), path.alias("path"), common.clean_text(common.col(text)).alias("text"))
    rows = common.identified(rows, "doc_id", ["doc_id", "path", "text"])
    found = notices(rows.select("uid", "text")).filter(F.col("similarity") >= LEAST)
    large = (F.col("kind") <= 1) & (F.col("similarity") >= FILE_LEAST)
    first = F.max(F.struct(large.alias("large"), "similarity", (-F.col("kind")).alias("kind"), (-F.col("place")).alias("place"), "license")).alias("best")
    whole = F.max(F.when(F.col("kind") == 0, F.struct("similarity", "license"))).alias("whole")
    own = found.groupBy("uid").agg(first, whole).select("uid", "best.license", "best.similarity", F.element_at(F.array(*map(F.lit, KINDS)), 1 - F.col("best.kind")).alias("part"), "whole")
    own = common.stage(own, "license-own")
    told = rows.select("uid", "ord", "doc_id", "path").join(own.hint("merge"), "uid", "left")
    files = told.filter(F.col("whole.similarity") >= FILE_LEAST).withColumn("dir", F.element_at(directories(F.col("path")), -1))
    given = files.groupBy("dir").agg(F.max(F.struct("whole.similarity", (-F.col("ord")).alias("o"), "whole.license")).alias("best"))
    given = common.stage(given.select(F.col("dir").alias("licence_dir"), F.col("best.license").alias("dir_license")), "license-dirs")
    out = told.join(inherited(told, given).hint("merge"), "uid", "left")
    origin = F.when(F.col("license").isNotNull(), F.lit("notice")).when(F.col("got").isNotNull(), F.lit("inherited")).otherwise(F.lit("none"))
    return out.select("doc_id", "path", F.coalesce("license", "got.dir_license").alias("license"), "similarity", "part", origin.alias("origin"), F.col("got.licence_dir").alias("licence_dir"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source", "lang")
    return license_scan(docs, F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string")))


def sql() -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    table = ", ".join(f"({i}, {quoted(n)}, {quoted(t)})" for i, (n, t) in enumerate(templates()))
    cut = licenses._CUT
    return rf"""
WITH template(t, license, words) AS (VALUES {table}),
d AS (SELECT doc_id, concat_ws('/', source, lang, CAST(doc_id AS VARCHAR)) AS path, concat_ws('/', source, lang) AS dir, source AS top, coalesce(text, '') AS text FROM documents),
share AS (SELECT term, count(*) / (SELECT count(*) FROM d) AS share FROM (SELECT unnest(list_distinct(string_split_regex(lower(text), '{cut}'))) AS term FROM d) GROUP BY term),
held AS (SELECT doc_id, text, string_split(text, chr(10)) AS lines FROM d WHERE regexp_matches(lower(text), '{TRIGGER}')),
split AS (SELECT doc_id, text, lines, coalesce(list_position(list_transform(lines, lambda x: regexp_matches(x, '{_COMMENT}')), false), 0) AS ends,
  string_split(array_to_string(list_transform(lines, lambda x: CASE WHEN regexp_matches(x, '{_BLANK}') THEN '' ELSE x END), chr(10)), chr(10) || chr(10)) AS paragraphs FROM held),
piece AS (
  SELECT doc_id, 0 AS kind, 1 AS place, text AS words FROM split
  UNION ALL SELECT doc_id, 1, 1, array_to_string(CASE WHEN ends > 0 THEN lines[1:ends - 1] ELSE lines END, chr(10)) FROM split
  UNION ALL SELECT doc_id, 2, generate_subscripts(paragraphs, 1), unnest(paragraphs) FROM split
  UNION ALL SELECT doc_id, 3, generate_subscripts(lines, 1), unnest(lines) FROM split),
term AS (SELECT doc_id, kind, place, term, count(*) AS tf FROM (SELECT doc_id, kind, place, unnest(string_split_regex(lower(words), '{cut}')) AS term FROM piece WHERE regexp_matches(lower(words), '{TRIGGER}')) WHERE term <> '' GROUP BY ALL),
tterm AS (SELECT t, license, term, count(*) AS tf FROM (SELECT t, license, unnest(string_split_regex(lower(words), '{cut}')) AS term FROM template) WHERE term <> '' GROUP BY ALL),
w AS (SELECT term.*, tf * (1 + ln((1 + {FLOOR}) / (share + {FLOOR}))) AS w FROM term JOIN share USING (term)),
tw AS (SELECT t, license, term, tf * (1 + ln((1 + {FLOOR}) / (coalesce(share, 0) + {FLOOR}))) AS tw FROM tterm LEFT JOIN share USING (term)),
tn AS (SELECT t, sqrt(sum(tw * tw)) AS tn FROM tw GROUP BY t),
norm AS (SELECT doc_id, kind, place, sqrt(sum(w * w)) AS norm FROM w GROUP BY ALL),
dots AS (SELECT doc_id, kind, place, t, license, sum(w * tw / tn) AS dot FROM w JOIN tw USING (term) JOIN tn USING (t) GROUP BY ALL),
near AS (SELECT doc_id, kind, place, t, license, round(dot / norm, 6) AS similarity FROM dots JOIN norm USING (doc_id, kind, place)),
best AS (SELECT * FROM near QUALIFY row_number() OVER (PARTITION BY doc_id, kind, place ORDER BY similarity DESC, t) = 1),
own AS (SELECT * FROM best WHERE similarity >= {LEAST} QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY (kind <= 1 AND similarity >= {FILE_LEAST}) DESC, similarity DESC, kind, place) = 1),
files AS (SELECT dir, license FROM best JOIN d USING (doc_id) WHERE kind = 0 AND similarity >= {FILE_LEAST} QUALIFY row_number() OVER (PARTITION BY dir ORDER BY similarity DESC, doc_id) = 1)
SELECT doc_id, path, coalesce(own.license, f2.license, f1.license) AS license, similarity,
  CASE kind WHEN 0 THEN 'file' WHEN 1 THEN 'head' WHEN 2 THEN 'paragraph' WHEN 3 THEN 'line' END AS part,
  CASE WHEN own.license IS NOT NULL THEN 'notice' WHEN f2.license IS NOT NULL OR f1.license IS NOT NULL THEN 'inherited' ELSE 'none' END AS origin,
  CASE WHEN own.license IS NULL THEN coalesce(f2.dir, f1.dir) END AS licence_dir
FROM d LEFT JOIN own USING (doc_id) LEFT JOIN files f2 ON f2.dir = d.dir LEFT JOIN files f1 ON f1.dir = d.top
"""
