"""License scans line by line: TF-IDF cosine of notice lines to templates, then inheritance from the nearest directory with a licence file.

The smaller form of the scan, for tables of short notices; `license_texts` does the whole job and is the one that is registered. All in built-in functions. Every line of every text that holds a trigger word is a candidate. Terms are weighted by
inverse document frequencies counted over all documents; a line's vector holds all its terms, those outside the templates
with the weight of a term never seen. A line's similarity is its best cosine over the templates. A document that is
mostly notice is a licence file and speaks for its directory; a document without a notice of its own takes the licence
of its nearest ancestor directory, found by an equality join on directory paths.

Defined results: null or empty texts have no notice and may inherit. A null part of the path is left out of it. Of equal similarities the
earliest line counts, then the first name; of several licence files in a directory the most similar, then the
one with the least id. Rows with equal ids are told apart. Broadcast are the templates alone, a fixed table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

# fixed values: notices and openings of common licences
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "you may not use this file except in compliance with the License"),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "Creative Commons Attribution-NonCommercial 4.0 International Public License"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("proprietary", "All rights reserved."),
)
TRIGGER = "licen[sc]|copyright|reserved|permission|permitted|redistribut|creative commons|public domain"
LEAST, FILE_SHARE = 0.6, 0.5
_CUT = "[^a-z0-9]+"


def terms(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), _CUT), lambda w: w != "")


def _vocabulary() -> list[str]:
    import re

    return sorted({w for _, t in TEMPLATES for w in re.split(_CUT, t.lower()) if w})


def idf(texts: DataFrame) -> DataFrame:
    """term, weight of every template term, and '' for terms outside; frequencies count all texts."""
    spark = texts.sparkSession
    words = _vocabulary()
    listed = F.array(*[F.lit(w) for w in words])
    seen = texts.select(F.explode(F.array_intersect(F.split(F.lower("text"), _CUT), listed)).alias("term"))
    df = seen.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    total = texts.agg(F.count(F.lit(1)).alias("n"))
    every = spark.range(1).select(F.explode(F.array(*[F.lit(w) for w in [*words, ""]])).alias("term"))
    weight = F.log((F.col("n") + 1) / (F.coalesce("df", F.lit(0)) + 1)) + 1
    return every.join(df, "term", "left").crossJoin(F.broadcast(total)).select("term", weight.alias("weight"))


def notices(texts: DataFrame) -> DataFrame:
    """uid, line, license, similarity, share (of the text's characters) of each candidate line's best template; texts: uid, text."""
    spark = texts.sparkSession
    weights = common.stage(idf(texts), "license-idf")  # a row per template term
    lines = texts.select("uid", F.length("text").alias("size"), F.posexplode(F.split("text", "\n", -1)).alias("line", "words")).filter(F.lower("words").rlike(TRIGGER))
    lines = lines.withColumn("share", F.length("words") / F.col("size"))
    counted = lines.select("uid", "line", "share", F.explode(terms(F.col("words"))).alias("term")).groupBy("uid", "line", "share", "term").agg(F.count(F.lit(1)).alias("tf"))
    known = F.array(*[F.lit(w) for w in _vocabulary()])
    counted = counted.withColumn("base", F.when(F.array_contains(known, F.col("term")), F.col("term")).otherwise(F.lit("")))
    small = F.broadcast(weights.withColumnRenamed("term", "base"))
    counted = counted.join(small, "base").withColumn("w", F.col("tf") * F.col("weight"))
    each = [F.struct(F.lit(i).alias("t"), F.lit(n).alias("license"), F.lit(t).alias("words")) for i, (n, t) in enumerate(TEMPLATES)]
    template = spark.range(1).select(F.inline(F.array(*each)))
    template = template.select("t", "license", F.explode(terms(F.col("words"))).alias("term")).groupBy("t", "license", "term").agg(F.count(F.lit(1)).alias("tf"))
    template = template.join(weights, "term").withColumn("tw", F.col("tf") * F.col("weight"))
    length = template.groupBy("t").agg(F.sqrt(F.sum(F.col("tw") * F.col("tw"))).alias("tn"))
    template = template.join(length, "t").select("t", "license", "term", (F.col("tw") / F.col("tn")).alias("tw"))
    norm = counted.groupBy("uid", "line", "share").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = counted.join(F.broadcast(template), "term").groupBy("uid", "line", "t", "license").agg(F.sum(F.col("w") * F.col("tw")).alias("dot"))
    near = dots.join(norm, ["uid", "line"]).withColumn("similarity", F.round(F.col("dot") / F.col("norm"), 6))
    best = F.max(F.struct("similarity", (-F.col("t")).alias("t"), "license")).alias("best")
    return near.groupBy("uid", "line", "share").agg(best).select("uid", "line", "share", "best.license", "best.similarity")


def directories(path: Column) -> Column:
    """All ancestor directories of a path, from the root down."""
    part = F.split(path, "/")
    return F.transform(F.sequence(F.lit(1), F.greatest(F.size(part) - 1, F.lit(1))), lambda i: F.array_join(F.slice(part, F.lit(1), i), "/"))


#: Parts that the documents of one directory are dealt to when they look for its licence.
SALTS = 16


def inherited(told: DataFrame, given: DataFrame) -> DataFrame:
    """uid and got (depth, licence_dir, dir_license) of documents without a notice: their nearest directory that has a licence.

    told has uid, path, license; given licence_dir, dir_license. A directory may hold a third of all documents: these are dealt to
    `SALTS` parts by their uid, and the licences, a row per licence file's directory, stand in each part.
    """
    bare = told.filter(F.col("license").isNull()).select("uid", F.posexplode(directories(F.col("path"))).alias("depth", "dir"))
    bare = bare.withColumn("salt", F.pmod(F.xxhash64("uid"), F.lit(SALTS)).cast("int"))
    every = given.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    met = bare.join(every.hint("merge"), (F.col("dir") == F.col("licence_dir")) & (F.col("salt") == F.col("part")))
    return met.groupBy("uid").agg(F.max(F.struct("depth", "licence_dir", "dir_license")).alias("got"))


def license_scan(docs: DataFrame, path: Column, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Per row: doc_id, path, license, similarity, origin (notice, inherited or none), licence_dir."""
    rows = docs.select(common.col(key).cast("long").alias("doc_id"), path.alias("path"), common.clean_text(common.col(text)).alias("text"))
    rows = common.identified(rows, "doc_id", ["doc_id", "path", "text"])
    found = notices(rows.select("uid", "text")).filter(F.col("similarity") >= LEAST)
    first = F.max(F.struct("similarity", (-F.col("line")).alias("line"), "license")).alias("best")
    own = found.groupBy("uid").agg(first, F.sum("share").alias("share"))
    own = common.stage(own.select("uid", F.col("best.license").alias("license"), F.col("best.similarity").alias("similarity"), "share"), "license-own")
    told = rows.select("uid", "ord", "doc_id", "path").join(own.hint("merge"), "uid", "left")
    last = lambda c: F.element_at(directories(c), -1)
    files = told.filter(F.col("share") >= FILE_SHARE).withColumn("dir", last(F.col("path")))
    given = files.groupBy("dir").agg(F.max(F.struct("similarity", (-F.col("ord")).alias("o"), "license")).alias("best"))
    given = common.stage(given.select(F.col("dir").alias("licence_dir"), F.col("best.license").alias("dir_license")), "license-dirs")
    out = told.join(inherited(told, given).hint("merge"), "uid", "left")
    origin = F.when(F.col("license").isNotNull(), F.lit("notice")).when(F.col("got").isNotNull(), F.lit("inherited")).otherwise(F.lit("none"))
    return out.select("doc_id", "path", F.coalesce("license", "got.dir_license").alias("license"), "similarity", origin.alias("origin"), F.col("got.licence_dir").alias("licence_dir"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source", "lang")
    return license_scan(docs, F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string")))


def _sql() -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    table = ", ".join(f"({i}, {quoted(n)}, {quoted(t)})" for i, (n, t) in enumerate(TEMPLATES))
    return rf"""
WITH template(t, license, words) AS (VALUES {table}),
tterm AS (SELECT t, license, term, count(*) AS tf FROM (SELECT t, license, unnest(string_split_regex(lower(words), '{_CUT}')) AS term FROM template) WHERE term <> '' GROUP BY ALL),
vocabulary AS (SELECT DISTINCT term FROM tterm UNION ALL SELECT ''),
d AS (SELECT doc_id, concat_ws('/', source, lang, CAST(doc_id AS VARCHAR)) AS path, concat_ws('/', source, lang) AS dir, source AS top, coalesce(text, '') AS text FROM documents),
seen AS (SELECT term, count(*) AS df FROM (SELECT unnest(list_distinct(string_split_regex(lower(text), '{_CUT}'))) AS term FROM d) WHERE term <> '' GROUP BY term),
weights AS (SELECT v.term, ln(((SELECT count(*) FROM d) + 1) / (coalesce(df, 0) + 1)) + 1 AS weight FROM vocabulary v LEFT JOIN seen USING (term)),
line AS (SELECT doc_id, line, words, length(words) / length(text) AS share FROM (SELECT doc_id, text, unnest(string_split(text, chr(10))) AS words, generate_subscripts(string_split(text, chr(10)), 1) AS line FROM d) WHERE regexp_matches(lower(words), '{TRIGGER}')),
counted AS (SELECT doc_id, line, share, term, count(*) AS tf FROM (SELECT doc_id, line, share, unnest(string_split_regex(lower(words), '{_CUT}')) AS term FROM line) WHERE term <> '' GROUP BY ALL),
weighed AS (SELECT c.*, tf * w.weight AS w FROM counted c JOIN weights w ON w.term = CASE WHEN c.term IN (SELECT term FROM vocabulary) THEN c.term ELSE '' END),
tw AS (SELECT t, license, term, tf * weight AS tw FROM tterm JOIN weights USING (term)),
tn AS (SELECT t, sqrt(sum(tw * tw)) AS tn FROM tw GROUP BY t),
norm AS (SELECT doc_id, line, share, sqrt(sum(w * w)) AS norm FROM weighed GROUP BY ALL),
dots AS (SELECT doc_id, line, t, license, sum(w * tw / tn) AS dot FROM weighed JOIN tw USING (term) JOIN tn USING (t) GROUP BY ALL),
near AS (SELECT doc_id, line, share, t, license, round(dot / norm, 6) AS similarity FROM dots JOIN norm USING (doc_id, line)),
best AS (SELECT * FROM near QUALIFY row_number() OVER (PARTITION BY doc_id, line ORDER BY similarity DESC, t) = 1),
fit AS (SELECT * FROM best WHERE similarity >= {LEAST}),
own AS (SELECT doc_id, license, similarity, sum(share) OVER (PARTITION BY doc_id) AS share FROM fit QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY similarity DESC, line) = 1),
files AS (SELECT dir, license FROM own JOIN d USING (doc_id) WHERE share >= {FILE_SHARE} QUALIFY row_number() OVER (PARTITION BY dir ORDER BY similarity DESC, doc_id) = 1)
SELECT doc_id, path, coalesce(own.license, f2.license, f1.license) AS license, similarity,
  CASE WHEN own.license IS NOT NULL THEN 'notice' WHEN f2.license IS NOT NULL OR f1.license IS NOT NULL THEN 'inherited' ELSE 'none' END AS origin,
  CASE WHEN own.license IS NULL THEN coalesce(f2.dir, f1.dir) END AS licence_dir
FROM d LEFT JOIN own USING (doc_id) LEFT JOIN files f2 ON f2.dir = d.dir LEFT JOIN files f1 ON f1.dir = d.top
"""


SQL = _sql()
