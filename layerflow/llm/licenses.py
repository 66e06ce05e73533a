"""License scans: TF-IDF cosine of headers and license files to templates, and inheritance from directories.

Every line of a text that speaks of a license is a header.  Its words, weighted by term frequency and by how few
templates hold them, make a sparse vector; its cosine to each template's vector comes from one join on words with the
templates' weights, a table of fixed size.  The best template at or above ``LEAST`` names the license.

A file is a license file if its name says so or if it holds nothing but headers.  Its whole text makes one more vector,
with logarithms of the term frequencies, which is compared in the same way with the texts in ``license_texts``; the
best of them at or above ``LEAST_WHOLE`` goes before what its lines say.  ``TITLES`` tells licenses apart whose texts
share most of their words.  The nearest directory above a file
with a license file gives the license to files that state none: directories (not files) list their ancestors, which are
joined with the licensed directories by path, and the deepest match counts.

DataFrame functions only.  Defined results: null and empty texts state nothing; of equally near templates the first in
order wins; of several license files in one directory the best-scoring one counts; a null path has no directory, so
it inherits nothing and gives nothing, but states what its own lines say; files of one path with different texts are
judged by their own; other columns stay as they are, those named like a result are replaced by it.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from pathlib import Path

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LEAST = 0.6
CUE = r"(?i)licen[cs]e|copyright|spdx|public domain|all rights reserved"
LICENSE_NAME = r"(?i)^(licen[cs]e|copying|unlicense|notice)([._-].*)?$"
SPLIT = r"[^a-z0-9]+"
#: Below it lie, of the texts tried, those of other licenses (at most 0.70) that no title tells apart.
LEAST_WHOLE = 0.75
TEXTS = Path(__file__).with_name("license_texts")
#: Of the nearest whole text, what in a lower-cased text shows that it is another license's, and which one if it has a name here.
TITLES = (
    ("GPL-3.0", r"gnu affero general public license\s+version 3,", "AGPL-3.0"),
    ("GPL-2.0", r"gnu (lesser|library) general public license\s+version 2", None),
    ("GPL-2.0", r"general public license\s+version 1,", None),
    ("CC-BY-SA-4.0", r"attribution-(noncommercial-|noderiv)", None),
    ("CC-BY-SA-4.0", r"attribution-noncommercial 4\.0 international", "CC-BY-NC-4.0"),
    ("CC-BY-SA-4.0", r"attribution 4\.0 international", "CC-BY-4.0"),
    ("BSD-2-Clause", r"all\s+advertising\s+materials", None),
    ("BSD-3-Clause", r"all\s+advertising\s+materials", None),
    ("BSD-2-Clause", r"neither\s+the\s+names?\b", "BSD-3-Clause"),
    ("BSD-3-Clause", r"(?s)\A(?!.*neither\s+the\s+names?\b)", "BSD-2-Clause"),
)

#: Headers and first lines of license files, by SPDX identifier.
TEMPLATES = (
    ("AGPL-3.0", "This program is licensed under the GNU Affero General Public License, version 3."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("BSD-2-Clause", "Licensed under the BSD 2-Clause License."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the copyright notice is retained."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "Creative Commons Attribution 4.0 International License"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "Creative Commons Attribution-NonCommercial 4.0 International License"),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-SA-4.0", "Creative Commons Attribution-ShareAlike 4.0 International License"),
    ("CC0-1.0", "Dedicated to the public domain under CC0 1.0 Universal."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("ISC", "Released under the ISC License."),
    ("LGPL-3.0", "This library is licensed under the GNU Lesser General Public License, version 3."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software, to deal in it without restriction, under this license."),
    ("MPL-2.0", "This source code is subject to the terms of the Mozilla Public License, version 2.0."),
    ("Unlicense", "This is free and unencumbered software released into the public domain. The Unlicense."),
)


def _words(text: str) -> list[str]:
    return [w for w in re.split(SPLIT, text.lower()) if w]


def template_weights() -> tuple[list[tuple[int, str, str, float]], dict[str, float], float]:
    """(template, license, word, unit weight) of all templates, the words' idf, and that of any other word."""
    tf = [Counter(_words(text)) for _, text in TEMPLATES]
    df = Counter(w for c in tf for w in c)
    idf = {w: math.log((1 + len(tf)) / (1 + n)) + 1 for w, n in df.items()}
    rows = []
    for i, ((name, _), c) in enumerate(zip(TEMPLATES, tf)):
        norm = math.sqrt(sum((n * idf[w]) ** 2 for w, n in c.items()))
        rows += [(i, name, w, n * idf[w] / norm) for w, n in c.items()]
    return rows, idf, math.log(1 + len(tf)) + 1


def whole_weights() -> tuple[list[tuple[str, str, float]], dict[str, float], float]:
    """(license, word, unit weight) of the whole texts, the words' idf, and that of any other word."""
    tf = {f.stem: Counter(_words(f.read_text())) for f in sorted(TEXTS.glob("*.txt"))}
    df = Counter(w for c in tf.values() for w in c)
    idf = {w: math.log((1 + len(tf)) / (1 + n)) + 1 for w, n in df.items()}
    rows = []
    for name, c in tf.items():
        weight = {w: (1 + math.log(n)) * idf[w] for w, n in c.items()}
        norm = math.sqrt(sum(x * x for x in weight.values()))
        rows += [(name, w, x / norm) for w, x in weight.items()]
    return rows, idf, math.log(1 + len(tf)) + 1


def directory(path: Column) -> Column:
    return F.regexp_replace(path, "/?[^/]*$", "")


def keyed(files: DataFrame) -> DataFrame:
    """Files with a key of path and text: files that share a path keep their own lines, equal ones share an answer."""
    one = lambda c: F.concat(F.when(F.col(c).isNull(), F.lit("-")).otherwise(F.lit("+")), F.coalesce(F.col(c), F.lit("")))
    return files.withColumn("_key", F.md5(F.concat(F.md5(one("path").cast("binary")), one("text")).cast("binary")))


def headers(files: DataFrame) -> DataFrame:
    """(_key, line, header) of all lines with a cue."""
    lines = F.split(F.coalesce("text", F.lit("")), "\n")
    return files.where(F.col("text").rlike(CUE)).select("_key", F.posexplode(F.filter(lines, lambda x: x.rlike(CUE))).alias("line", "header"))


def scores(lines: DataFrame) -> DataFrame:
    """(_key, license, score): each file's best template over its headers."""
    rows, idf, other = template_weights()
    spark = lines.sparkSession
    weights = F.broadcast(spark.createDataFrame(rows, "template int, license string, word string, weight double"))
    rarity = F.broadcast(spark.createDataFrame(list(idf.items()), "word string, idf double"))
    words = lines.select("_key", "line", F.explode(F.split(F.lower("header"), SPLIT)).alias("word")).where("word != ''")
    tf = words.groupBy("_key", "line", "word").agg(F.count("*").alias("n"))
    tf = tf.join(rarity, "word", "left").select("_key", "line", "word", (F.col("n") * F.coalesce("idf", F.lit(other))).alias("w"))
    norm = tf.groupBy("_key", "line").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = tf.join(weights, "word").groupBy("_key", "line", "template", "license").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"))
    cos = dots.join(norm, ["_key", "line"]).select("_key", "license", F.round(F.col("dot") / F.col("norm"), 6).alias("score"))
    best = cos.where(F.col("score") >= LEAST).groupBy("_key").agg(F.max("score").alias("score"), F.min(F.struct((-F.col("score")).alias("s"), "license")).alias("b"))
    return best.select("_key", F.col("b.license").alias("license"), "score")


def _is_license_file() -> Column:
    """By name, or because every line that isn't blank is a header."""
    lines = F.filter(F.split(F.coalesce("text", F.lit("")), "\n"), lambda x: F.trim(x) != "")
    only = (F.size(lines) > 0) & F.forall(lines, lambda x: x.rlike(CUE))
    return F.regexp_extract("path", "[^/]*$", 0).rlike(LICENSE_NAME) | (F.col("text").rlike(CUE) & only)


def license_files(files: DataFrame) -> DataFrame:
    """(_key, path) of license files."""
    return files.where(_is_license_file()).where("path is not null").select("_key", "path").distinct()


def whole_scores(files: DataFrame) -> DataFrame:
    """(_key, license, score): of each license file the nearest whole text."""
    rows, idf, other = whole_weights()
    spark = files.sparkSession
    weights = F.broadcast(spark.createDataFrame(rows, "license string, word string, weight double"))
    rarity = F.broadcast(spark.createDataFrame(list(idf.items()), "word string, idf double"))
    low = F.lower("text")
    shown = F.array(*[low.rlike(pattern) for _, pattern, _ in TITLES])
    key = ["_key", "shown"]
    words = files.where(_is_license_file()).select("_key", shown.alias("shown"), F.explode(F.split(low, SPLIT)).alias("word")).where("word != ''")
    tf = words.groupBy(*key, "word").agg(F.count("*").alias("n"))
    tf = tf.join(rarity, "word", "left").select(*key, "word", ((F.log("n") + 1) * F.coalesce("idf", F.lit(other))).alias("w"))
    norm = tf.groupBy(key).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = tf.join(weights, "word").groupBy(*key, "license").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"))
    cos = dots.join(norm, key).select(*key, "license", F.round(F.col("dot") / F.col("norm"), 6).alias("score"))
    nearest = cos.where(F.col("score") >= LEAST_WHOLE).groupBy(key).agg(F.min(F.struct((-F.col("score")).alias("s"), "license", "score")).alias("b"))
    named = F.col("b.license")
    for i, (license, _, name) in reversed(list(enumerate(TITLES))):
        named = F.when((F.col("b.license") == license) & F.col("shown")[i], F.lit(name)).otherwise(named)
    return nearest.select("_key", named.alias("license"), "b.score").where("license is not null")


def scan_licenses(files: DataFrame) -> DataFrame:
    """Every row of ``files`` (path, text and more) without its text, with license, how (own, inherited, none), score and licensed_by."""
    added = ("license", "how", "score", "licensed_by")
    names = [c for c in files.columns if c.lower() not in (*added, "text")]
    files = keyed(files.select("path", "text", F.struct(*names).alias("_row")))
    whole = whole_scores(files)
    own = whole.unionByName(scores(headers(files)).join(whole, "_key", "left_anti"))
    named = license_files(files).join(own, "_key").select(directory(F.col("path")).alias("_dir"), F.struct((-F.col("score")).alias("s"), "license", "path").alias("b"))
    licensed = named.groupBy("_dir").agg(F.min("b").alias("b")).select(F.col("_dir").alias("ancestor"), F.col("b.license").alias("up"), F.col("b.path").alias("by"))
    parts = F.split("_dir", "/")
    dirs = files.select(directory(F.col("path")).alias("_dir")).where("_dir is not null").distinct()
    up = dirs.select("_dir", F.explode(F.concat(F.array(F.lit("")), F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.array_join(F.slice(parts, F.lit(1), k), "/")))).alias("ancestor")).distinct()
    near = up.join(licensed, "ancestor").groupBy("_dir").agg(F.max(F.struct(F.length("ancestor").alias("l"), "up", "by")).alias("b")).select("_dir", "b.up", "b.by")
    out = files.select("_key", "_row", directory(F.col("path")).alias("_dir")).join(own, "_key", "left").join(near, "_dir", "left")
    how = F.when(F.col("license").isNotNull(), "own").when(F.col("up").isNotNull(), "inherited").otherwise("none")
    return out.select("_row.*", F.coalesce("license", "up").alias("license"), how.alias("how"), "score", F.when(how == "inherited", F.col("by")).alias("licensed_by"))


def document_path(key: str = "doc_id", source: str = "source") -> Column:
    """Documents as files of their source's tree: source/thousand/hundred/id.txt."""
    div = lambda n: F.call_function("div", F.col(key), F.lit(n)).cast("string")
    return F.concat_ws("/", F.coalesce(F.col(source), F.lit("none")), F.coalesce(div(1000), F.lit("x")), F.coalesce(div(100), F.lit("x")), F.concat(F.coalesce(F.col(key).cast("string"), F.lit("x")), F.lit(".txt")))


def oracle() -> str:
    """The same in SQL, for a checking database."""
    rows, idf, other = template_weights()
    q = lambda s: "'" + s.replace("'", "''") + "'"
    weights = ", ".join(f"({i}, {q(a)}, {q(b)}, {c!r})" for i, a, b, c in rows)
    rarity = ", ".join(f"({q(w)}, {v!r})" for w, v in idf.items())
    cue = CUE.removeprefix("(?i)")
    return f"""WITH weights(template, license, word, weight) AS (VALUES {weights}), rarity(word, idf) AS (VALUES {rarity}),
    files AS (SELECT doc_id, source || '/' || CAST(doc_id // 1000 AS VARCHAR) || '/' || CAST(doc_id // 100 AS VARCHAR) || '/' || CAST(doc_id AS VARCHAR) || '.txt' AS path,
        source || '/' || CAST(doc_id // 1000 AS VARCHAR) || '/' || CAST(doc_id // 100 AS VARCHAR) AS dir, string_split(text, chr(10)) AS lines FROM documents),
    headed AS (SELECT path, unnest(range(0, len(l))) AS line, unnest(l) AS header FROM (SELECT path, list_filter(lines, lambda x: regexp_matches(x, '{cue}', 'i')) AS l FROM files)),
    tf AS (SELECT path, line, word, count(*) AS n FROM (SELECT path, line, unnest(regexp_split_to_array(lower(header), '{SPLIT}')) AS word FROM headed) WHERE word <> '' GROUP BY 1, 2, 3),
    w AS (SELECT path, line, word, n * coalesce(idf, {other!r}) AS w FROM tf LEFT JOIN rarity USING (word)),
    cos AS (SELECT d.path, license, round(dot / norm, 6) AS score FROM (SELECT path, line, template, license, sum(w * weight) AS dot FROM w JOIN weights USING (word) GROUP BY 1, 2, 3, 4) d JOIN (SELECT path, line, sqrt(sum(w * w)) AS norm FROM w GROUP BY 1, 2) m USING (path, line)),
    own AS (SELECT path, license, score FROM (SELECT *, row_number() OVER (PARTITION BY path ORDER BY score DESC, license) AS r FROM cos WHERE score >= {LEAST}) WHERE r = 1),
    full_ AS (SELECT f.path, f.dir, o.license, o.score FROM files f JOIN own o USING (path) WHERE len(list_filter(lines, lambda x: trim(x) <> '')) > 0 AND len(list_filter(lines, lambda x: trim(x) <> '' AND NOT regexp_matches(x, '{cue}', 'i'))) = 0),
    licensed AS (SELECT dir AS anc, license AS up, path AS by_ FROM (SELECT *, row_number() OVER (PARTITION BY dir ORDER BY score DESC, license, path) AS r FROM full_) WHERE r = 1),
    ups AS (SELECT DISTINCT dir, dir AS anc, 3 AS depth FROM files UNION ALL SELECT DISTINCT dir, regexp_replace(dir, '/[^/]*$', ''), 2 FROM files UNION ALL SELECT DISTINCT dir, regexp_replace(dir, '/[^/]*/[^/]*$', ''), 1 FROM files UNION ALL SELECT DISTINCT dir, '', 0 FROM files),
    near_ AS (SELECT dir, up, by_ FROM (SELECT dir, up, by_, row_number() OVER (PARTITION BY dir ORDER BY depth DESC) AS r FROM ups JOIN licensed USING (anc)) WHERE r = 1)
    SELECT doc_id, files.path, coalesce(own.license, up) AS license, CASE WHEN own.license IS NOT NULL THEN 'own' WHEN up IS NOT NULL THEN 'inherited' ELSE 'none' END AS how, score, CASE WHEN own.license IS NULL AND up IS NOT NULL THEN by_ END AS licensed_by
    FROM files LEFT JOIN own USING (path) LEFT JOIN near_ ON near_.dir = files.dir"""
