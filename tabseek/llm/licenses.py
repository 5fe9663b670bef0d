"""License scans in DataFrame expressions only.

Every line of a whole text that holds a licensing cue becomes a sparse TF-IDF
vector over the templates' terms and is compared with each template by cosine.
So do blocks of lines around each cue, against whole headers, and the whole text,
against whole licence texts. A licence text decides a document's own license,
else its best line or block does. A document that is a licence text, is little
more than license lines, or has a license and a licence file's name is a licence
file and speaks for its directory. Documents without a license of their own
inherit from the nearest ancestor directory that has one, found by joining paths.

Templates are a fixed list, so weights are literals in the plan: nothing is
broadcast or collected. Texts and blocks of any length are compared; a block is
cut from its lines only while it is compared. Directories are made distinct
before they are joined.

Defined cases: a null text or path has no license and no directory; equal scores
go to the template first in the list, equal votes for a directory to the smaller
license name; repeated rows are scanned each for themselves, and each votes for
its directory; a text of any length is scanned whole, line by line; an empty
table gives no rows; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import math
import re
from pathlib import Path

from pyspark.sql import Column, DataFrame, functions as F

from .store import materialise

#: License id and wording of headers or of a licence file's first lines.
TEMPLATES = [
    ("Apache-2.0", "licensed under the apache license version 2.0"),
    ("Apache-2.0", "apache license version 2.0 january 2004"),
    ("MIT", "released under the mit license"),
    ("MIT", "permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("GPL-3.0", "this work is licensed under the gnu general public license version 3"),
    ("GPL-2.0", "gnu general public license version 2"),
    ("LGPL-3.0", "gnu lesser general public license version 3"),
    ("AGPL-3.0", "gnu affero general public license version 3"),
    ("BSD-3-Clause", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("BSD-3-Clause", "licensed under the bsd 3 clause license"),
    ("MPL-2.0", "mozilla public license version 2.0"),
    ("CC-BY-4.0", "licensed under cc by 4.0"),
    ("CC-BY-SA-4.0", "licensed under cc by sa 4.0"),
    ("CC-BY-NC-4.0", "licensed under cc by nc 4.0"),
    ("CC0-1.0", "cc0 1.0 universal public domain dedication"),
    ("Proprietary", "copyright all rights reserved"),
]
CUE = r"(?i)licen[sc]e|copyright|rights reserved|public domain|hereby granted|redistribution"
TERM = r"[0-9a-z.]*[0-9a-z]"
MIN_SCORE = 0.6
#: Whole headers; a block of lines is compared with these.
_GNU = "this program is free software you can redistribute it and or modify it under the terms of the gnu {}general public license as published by the free software foundation either version {} of the license or at your option any later version"
_GNU_END = " this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the gnu {}general public license for more details you should have received a copy of the gnu {}general public license along with this program"
_KINDS = [("GPL-3.0", "", "3"), ("GPL-2.0", "", "2"), ("LGPL-3.0", "lesser ", "3"), ("AGPL-3.0", "affero ", "3")]
_APACHE = "you may not use this file except in compliance with the license you may obtain a copy of the license at http www.apache.org licenses license 2.0"
HEADERS = [
    *[(name, _GNU.format(kind, version)) for name, kind, version in _KINDS],
    *[(name, _GNU.format(kind, version) + _GNU_END.format(kind, kind)) for name, kind, version in _KINDS],
    ("GPL-3.0", "gnu general public license version 3 29 june 2007"),
    ("GPL-2.0", "gnu general public license version 2 june 1991"),
    ("LGPL-3.0", "gnu lesser general public license version 3 29 june 2007"),
    ("AGPL-3.0", "gnu affero general public license version 3 19 november 2007"),
    ("Apache-2.0", "apache license version 2.0 january 2004 http www.apache.org licenses"),
    ("Apache-2.0", "licensed under the apache license version 2.0 the license " + _APACHE),
    ("Apache-2.0", "licensed under the apache license version 2.0 the license " + _APACHE + " unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license"),
    ("MIT", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions"),
    ("BSD-3-Clause", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("MPL-2.0", "this source code form is subject to the terms of the mozilla public license v. 2.0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla.org mpl 2.0"),
]
#: Lines before and after a cue that a block takes.
REACH = [(a, b) for a in range(4) for b in range(4) if a + b] + [(0, 12), (1, 12), (3, 12)]
#: A whole text this near a licence text is one.
TEXT_SCORE = 0.8
FILE_NAME = r"(?i)(^|/)(un)?(licen[sc]e|copying)([.-][^/]*)?$"
#: A licence file's cue lines hold at least this share of its characters.
FILE_SHARE = 0.5


#: (license id, terms) of whole licence texts.
TEXTS = [(p.stem, " ".join(re.findall(TERM, p.read_text().lower()))) for p in sorted((Path(__file__).parent / "license_texts").glob("*.txt"))]


def _weights(templates: list[tuple[str, str]] = TEMPLATES) -> tuple[dict[str, float], list[tuple[str, dict[str, float]]]]:
    """Inverse document frequencies over the templates, and the templates' unit vectors."""
    bags = [(name, text.split()) for name, text in templates]
    n = len(bags)
    df = {t: sum(t in words for _, words in bags) for _, bag in bags for t in bag}
    idf = {t: math.log((1 + n) / (1 + d)) + 1 for t, d in df.items()}
    unit = []
    for name, words in bags:
        vector = {t: words.count(t) * idf[t] for t in dict.fromkeys(words)}
        norm = math.sqrt(sum(v * v for v in vector.values()))
        unit.append((name, {t: v / norm for t, v in vector.items()}))
    return idf, unit


IDF, UNIT = _weights()
#: The weight of terms that no template has: they lengthen a line's vector only.
UNKNOWN = math.log(1 + len(TEMPLATES)) + 1


def _map(values: dict[str, float]) -> Column:
    return F.create_map(*[F.lit(x) for t, v in values.items() for x in (t, v)])


def _dot(terms: Column, weights: dict[str, float]) -> Column:
    """Sum over a line's terms; a term that stands twice counts twice, as its frequency asks."""
    table = _map({t: w * IDF[t] for t, w in weights.items()})
    return F.aggregate(terms, F.lit(0.0), lambda s, t: s + F.coalesce(F.element_at(table, t), F.lit(0.0)))


def _nearest(texts: Column, templates: list[tuple[str, str]], text_of=lambda x: x) -> Column:
    """The best (score, order, name) of several texts, null for none; linear in a text's terms. ``text_of`` makes one from an item of ``texts``."""
    idf, unit = _weights(templates)
    rows = ",".join(f"{t}:{v!r} " + " ".join(repr(round(w.get(t, 0.0) * v, 9)) for _, w in unit) for t, v in idf.items())
    table = F.str_to_map(F.lit(rows), F.lit(","), F.lit(":"))  # a literal in the plan
    unknown = F.lit(" ".join([repr(math.log(1 + len(templates)) + 1)] + ["0.0"] * len(unit)))
    let = lambda value, body: F.transform(F.array(value), body)[0]

    def runs(terms: Column) -> Column:
        starts = F.filter(F.transform(terms, lambda t, i: F.when((i == 0) | (t != F.get(terms, i - 1)), i)), lambda i: i.isNotNull())
        return let(starts, lambda s: F.transform(s, lambda i, k: F.struct(F.get(terms, i).alias("term"), (F.coalesce(F.get(s, k + 1), F.size(terms)) - i).alias("tf"))))

    def vector(run: Column) -> Column:
        return F.transform(F.split(F.coalesce(F.element_at(table, run["term"]), unknown), " "), lambda x: x.cast("double") * run["tf"])

    def best(vectors: Column) -> Column:
        norm = F.sqrt(F.aggregate(vectors, F.lit(0.0), lambda s, v: s + v[0] * v[0]))
        dots = F.aggregate(vectors, F.array_repeat(F.lit(0.0), len(unit) + 1), lambda s, v: F.zip_with(s, v, lambda x, y: x + y))
        names = F.split(F.lit(" ".join(name for name, _ in unit)), " ")
        return let(norm, lambda n: F.array_max(F.transform(F.slice(dots, 2, len(unit)), lambda d, i: F.struct(F.round(F.when(n > 0, d / n).otherwise(0.0), 6).alias("score"), (-i).alias("order"), F.get(names, i).alias("name")))))

    terms = lambda text: F.array_sort(F.regexp_extract_all(F.lower(text), F.lit(TERM), F.lit(0)))
    return F.array_max(F.transform(texts, lambda text: let(terms(text_of(text)), lambda t: let(let(runs(t), lambda r: F.transform(r, vector)), best))))


def _blocks(lines: Column) -> Column:
    """Where the lines around each that holds a cue begin and end; each block of two lines or more once."""
    cued = F.filter(F.transform(lines, lambda x, i: F.when(x.rlike(CUE), i)), lambda i: i.isNotNull())
    reach = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a, b in REACH])
    spans = F.flatten(F.transform(cued, lambda i: F.transform(reach, lambda r: F.struct(F.greatest(i - r["a"], F.lit(0)).alias("s"), F.least(i + r["b"], F.size(lines) - 1).alias("e")))))
    return F.filter(F.array_distinct(spans), lambda x: x["e"] > x["s"])


def _nearest_block(lines: Column) -> Column:
    """``_nearest`` of the blocks, one of which is joined at a time."""
    return _nearest(_blocks(lines), HEADERS, lambda x: F.array_join(F.slice(lines, x["s"] + 1, x["e"] - x["s"] + 1), "\n"))


def own_licenses(docs: DataFrame) -> DataFrame:
    """``docs`` (doc_id, path, text) to doc_id, path, own_license, own_score, is_file."""
    text = F.coalesce(F.col("text"), F.lit(""))
    cued = text.rlike(CUE)
    split = F.split(text, "\n", -1)
    block = F.when(cued, F.transform(F.array(split), _nearest_block)[0])
    whole = F.when(cued, _nearest(F.array(text), TEXTS))
    lines = docs.select("doc_id", "path", F.length(text).alias("_chars"), F.filter(split, lambda x: x.rlike(CUE)).alias("_lines"), block.alias("_block"), whole.alias("_whole"))
    terms = lines.select("doc_id", "path", F.aggregate("_lines", F.lit(0), lambda s, x: s + F.length(x)).alias("_cued"), "_chars", "_block", "_whole", F.transform("_lines", lambda x: F.regexp_extract_all(F.lower(x), F.lit(TERM), F.lit(0))).alias("_terms"))
    idf = _map(IDF)

    def norm(line: Column) -> Column:
        counts = F.transform(F.array_distinct(line), lambda t: F.size(F.filter(line, lambda u: u == t)) * F.coalesce(F.element_at(idf, t), F.lit(UNKNOWN)))
        return F.sqrt(F.aggregate(counts, F.lit(0.0), lambda s, x: s + x * x))

    def best(line: Column) -> Column:
        scores = F.array(*[F.struct(F.round(_dot(line, w), 9).alias("dot"), F.lit(-i).alias("order"), F.lit(name).alias("name")) for i, (name, w) in enumerate(UNIT)])
        top = F.array_max(scores)
        return F.struct(F.round(F.when(norm(line) > 0, top["dot"] / norm(line)).otherwise(0.0), 6).alias("score"), top["order"].alias("order"), top["name"].alias("name"))

    top = terms.select("doc_id", "path", "_chars", "_cued", "_block", "_whole", F.array_max(F.transform("_terms", best)).alias("_line"))
    is_text = F.coalesce(F.col("_whole.score") >= TEXT_SCORE, F.lit(False))
    near = F.when(F.col("_block.score") > F.col("_line.score"), F.col("_block")).otherwise(F.col("_line"))
    top = top.select("doc_id", "path", "_chars", "_cued", is_text.alias("_is_text"), F.when(is_text, F.col("_whole")).otherwise(near).alias("_top"))
    hit = F.col("_top.score") >= MIN_SCORE
    is_file = hit & (F.col("_is_text") | (F.col("_cued") >= FILE_SHARE * F.col("_chars")) | F.coalesce(F.col("path").rlike(FILE_NAME), F.lit(False)))
    return top.select("doc_id", "path", F.when(hit, F.col("_top.name")).alias("own_license"), F.coalesce(F.col("_top.score"), F.lit(0.0)).alias("own_score"), F.coalesce(is_file, F.lit(False)).alias("is_file"))


def parent(path: Column) -> Column:
    """The directory of a path; null at the top."""
    return F.nullif(F.regexp_extract(path, "^(.*)/[^/]*$", 1), F.lit(""))


def scan(docs: DataFrame) -> DataFrame:
    """Per row of ``docs`` (doc_id, path, text): own_license, own_score, is_file, license, inherited_from."""
    own = materialise(own_licenses(docs).withColumn("dir", parent(F.col("path"))), "own-licenses")  # read three times below
    votes = own.where("is_file AND dir IS NOT NULL").groupBy("dir", "own_license").count()
    licensed = votes.groupBy("dir").agg(F.min(F.struct(-F.col("count"), "own_license"))["own_license"].alias("dir_license"))
    parts = F.split("dir", "/")
    ancestors = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.struct(i.alias("depth"), F.array_join(F.slice(parts, 1, i), "/").alias("at")))
    dirs = own.where("dir IS NOT NULL").select("dir").distinct().select("dir", F.explode(ancestors).alias("a"))
    near = dirs.join(licensed.select(F.col("dir").alias("at"), "dir_license"), F.col("a.at") == F.col("at")).groupBy("dir").agg(F.max(F.struct(F.col("a.depth").alias("depth"), "at", "dir_license")).alias("near"))
    joined = own.join(near, "dir", "left")
    inherits = F.col("own_license").isNull()
    return joined.select("doc_id", "path", "own_license", "own_score", "is_file", F.coalesce("own_license", "near.dir_license").alias("license"), F.when(inherits, F.col("near.at")).alias("inherited_from"))


def document_paths(docs: DataFrame) -> DataFrame:
    """``documents`` laid out as a tree: source, language, then hundreds of ids."""
    hundred = F.floor(F.col("doc_id") / 100).cast("string")
    return docs.select("doc_id", "text", F.concat_ws("/", F.coalesce("source", F.lit("unknown")), F.coalesce("lang", F.lit("unknown")), hundred, F.col("doc_id").cast("string")).alias("path"))


def oracle() -> str:
    """DuckDB SQL of ``scan`` over ``document_paths``."""
    template_rows = ", ".join(f"({-i}, '{name}', '{t}', {w * IDF[t]!r}::DOUBLE)" for i, (name, vector) in enumerate(UNIT) for t, w in vector.items())
    idf_rows = ", ".join(f"('{t}', {v!r}::DOUBLE)" for t, v in IDF.items())
    return rf"""
WITH docs AS (
  SELECT doc_id, coalesce(text, '') AS text,
         concat_ws('/', coalesce(source, 'unknown'), coalesce(lang, 'unknown'), CAST(CAST(floor(doc_id / 100) AS BIGINT) AS VARCHAR), CAST(doc_id AS VARCHAR)) AS path FROM documents),
vec(ord, name, term, w) AS (VALUES {template_rows}),
idf(term, v) AS (VALUES {idf_rows}),
lines AS (
  SELECT doc_id, i, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM docs)
  WHERE regexp_matches(line, '{CUE}')),
terms AS (SELECT doc_id, i, term, count(*) AS tf FROM (SELECT doc_id, i, unnest(regexp_extract_all(lower(line), '{TERM}')) AS term FROM lines) GROUP BY ALL),
norms AS (SELECT doc_id, i, sqrt(sum((tf * coalesce(v, {UNKNOWN!r})) ** 2)) AS norm FROM terms LEFT JOIN idf USING (term) GROUP BY ALL),
dots AS (SELECT doc_id, i, ord, name, round(sum(tf * w), 9) AS dot FROM terms JOIN vec USING (term) GROUP BY ALL),
line_best AS (
  SELECT doc_id, i, ord, name, round(dot / norm, 6) AS score
  FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, i ORDER BY dot DESC, ord DESC) AS k FROM dots) JOIN norms USING (doc_id, i) WHERE k = 1),
doc_best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, ord DESC) AS k FROM line_best) WHERE k = 1),
cued AS (SELECT doc_id, sum(length(line)) AS cued FROM lines GROUP BY doc_id),
own AS (
  SELECT docs.doc_id, path, regexp_extract(path, '^(.*)/[^/]*$', 1) AS dir, CASE WHEN score >= {MIN_SCORE} THEN name END AS own_license,
         coalesce(score, 0.0) AS own_score, coalesce(score >= {MIN_SCORE} AND cued >= {FILE_SHARE} * length(text), false) AS is_file
  FROM docs LEFT JOIN doc_best ON docs.doc_id = doc_best.doc_id LEFT JOIN cued ON docs.doc_id = cued.doc_id),
licensed AS (
  SELECT dir AS anc, own_license AS dir_license FROM (
    SELECT dir, own_license, row_number() OVER (PARTITION BY dir ORDER BY count(*) DESC, own_license) AS k FROM own WHERE is_file GROUP BY dir, own_license) WHERE k = 1),
near AS (
  SELECT d.dir, l.anc, l.dir_license, row_number() OVER (PARTITION BY d.dir ORDER BY length(l.anc) DESC) AS k
  FROM (SELECT DISTINCT dir FROM own) d JOIN licensed l ON d.dir = l.anc OR starts_with(d.dir, l.anc || '/'))
SELECT doc_id, path, own_license, own_score, is_file, coalesce(own_license, dir_license) AS license,
       CASE WHEN own_license IS NULL THEN anc END AS inherited_from
FROM own LEFT JOIN (SELECT * FROM near WHERE k = 1) n ON own.dir = n.dir
"""
