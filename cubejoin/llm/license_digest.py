"""Licence scans by canonical digest lookup.

A text is brought to a canonical form (ASCII case, copyright lines removed,
equivalent spellings unified, punctuation and space runs turned into one space)
and its digest is hash-joined with the digests of known licence texts.  The
whole document, each of its lines and paragraphs, and each run of as many
consecutive paragraphs as a known text has, are looked up, always as entire
texts: a licence inside the words of other paragraphs does not match.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Spellings that count as equal (written form, canonical form), applied in this order.
SPELLINGS = (
    ("licence", "license"),
    ("licenced", "licensed"),
    ("sub license", "sublicense"),
    ("sub-license", "sublicense"),
    ("non commercial", "noncommercial"),
    ("non-commercial", "noncommercial"),
    ("organisation", "organization"),
    ("favour", "favor"),
    ("merchantibility", "merchantability"),
    ("acknowledgement", "acknowledgment"),
    ("copyright holder", "copyright owner"),
    ("http://", "https://"),
)

#: Licence notices and short licence texts (identifier, text).
KNOWN = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.'),
    ("Apache-2.0", "Released under the Apache License 2.0."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "This project is licensed under the MIT License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "Licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-2.0", "Licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "Licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "Licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("BSD-2-Clause", "Licensed under the BSD 2-Clause License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC0-1.0", "Licensed under CC0 1.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-ND-4.0", "Licensed under CC BY-ND 4.0."),
    ("CC-BY-NC-SA-4.0", "Licensed under CC BY-NC-SA 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    (
        "MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    (
        "ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    (
        "0BSD",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
)

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Lines that are copyright notices: the word with (c), a year or a holder (not the words that follow it in licence bodies), a sign, or the reservation alone.
COPYRIGHT_LINE = (
    r"(?m)^[^a-z0-9\n]*(?:copyright(?![a-z0-9])(?![^a-z0-9\n]*(?:notices?|holders?|owners?|laws?|licen[sc]es?|licensors?|and|or|in|is|are|as|to|for|on|of|statements?|information|interests?|protection|ownership|treaty|disclaimers?)(?![a-z0-9]))[^\n]*"
    r"|\(c\)[ \t]*(?:copyright|by(?![a-z0-9])|[^\n]*(?<![0-9])(?:19|20)[0-9]{2}(?![0-9]))[^\n]*|\x{a9}[^\n]*|all rights reserved[^a-z0-9\n]*)$"
)
#: Title lines of the full texts in the catalogue.
TITLE_LINE = r"(?m)^[^a-z0-9\n]*(?:the )?(?:mit|expat|isc|0bsd|bsd[ -]zero[ -]clause|zero[ -]clause[ -]bsd|bsd[ -]0[ -]clause)(?:[ -]license)?[^a-z0-9\n]*(?:(?:mit|expat|isc|0bsd)(?:[ -]license)?)?[^a-z0-9\n]*$"
#: Lines without words part paragraphs, so that comment signs may stand in them.
PARTING = r"\n(?:[^a-z0-9\x{80}-\x{10FFFF}\n]*\n)+"
#: The SQL twin (whole texts, lines and single paragraphs) keeps its first rule for copyright lines.
SQL_COPYRIGHT_LINE = r"(?m)^[^a-z0-9\n]*(?:copyright|\(c\)|all rights reserved)[^\n]*$"
NOT_WORD = r"[^a-z0-9\x{80}-\x{10FFFF}]+"


def _spelled(text: Column) -> Column:
    """ASCII case, copyright lines and spellings; keeps line borders, and acts on each line alone."""
    out = F.translate(text, _UPPER, _LOWER)
    return _equal_spellings(F.regexp_replace(out, COPYRIGHT_LINE, ""))


def _equal_spellings(text: Column) -> Column:
    for written, form in SPELLINGS:
        text = F.replace(text, F.lit(written), F.lit(form))
    return text


def _spaced(text: Column) -> Column:
    return F.trim(F.regexp_replace(text, NOT_WORD, " "))


def canonical(text: Column) -> Column:
    """The form whose digest is looked up; idempotent for equal texts, null stays null."""
    return _spaced(_spelled(text))


def known_digests(spark: SparkSession) -> DataFrame:
    """(digest, license) of the built-in catalogue: a few dozen rows, a fixed size."""
    raw = spark.createDataFrame([*KNOWN], "license string, text string")
    return raw.select(F.sha2(canonical(F.col("text")), 256).alias("digest"), "license").distinct()


#: Numbers of paragraphs of the built-in texts.
PARAGRAPHS = tuple(sorted({len(re.split("\n[ \t]*\n", text)) for _, text in KNOWN}))


def _paragraph_runs(spelled: Column, lengths: tuple[int, ...]) -> Column:
    """(part, body) of each run of paragraphs, canonical; part 0 where the run is all of the document.

    Title lines part paragraphs as copyright lines do.  Spellings are unified
    again once a paragraph is one line, as a text may be wrapped between two words.
    """
    paragraphs = F.split(F.regexp_replace(spelled, TITLE_LINE, ""), PARTING)
    paragraphs = F.filter(F.transform(paragraphs, lambda x: _equal_spellings(_spaced(x))), lambda x: x != "")

    def run_of(of: Column, n: Column, k: int):
        return lambda i: F.struct(F.when(n == k, 0).otherwise(-1 - i - n * k).alias("part"), F.array_join(F.slice(of, i + 1, k), " ").alias("body"))

    def runs(of: Column) -> Column:
        n = F.size(of)
        found = []
        for k in lengths:
            every = F.transform(F.sequence(F.lit(0), n - k), run_of(of, n, k))
            # Single paragraphs are looked up as they stand in the text; here only one that is all of the document.
            found.append(F.when(n == k if k == 1 else n >= k, every).otherwise(F.array().cast("array<struct<part:int,body:string>>")))
        return F.concat(*found)

    return F.flatten(F.transform(F.array(paragraphs), runs))  # one evaluation of the paragraphs


def scan(spark: SparkSession, docs: DataFrame, catalogue: DataFrame | None = None, paragraphs: tuple[int, ...] = PARAGRAPHS) -> DataFrame:
    """One row per document: doc_id, n_texts (texts that are known licences), licenses, whole_license.

    ``licenses`` lists the distinct identifiers, sorted and comma-joined;
    ``whole_license`` is the identifier of the document as a whole, if any.
    Null or empty texts match nothing; rows are told apart by doc_id and text, so
    rows of one doc_id or without doc_id get the licences of their own text, and
    rows equal in both get equal results; an empty table gives no rows; extra
    columns are ignored, whatever their names; a user's ``catalogue`` (digest, license) of any size may replace the built-in
    one, which is broadcast because its size is fixed; ``paragraphs`` are the
    numbers of paragraphs of its texts.  Title and copyright lines around a
    full text do not count against the document as a whole.
    """
    known = F.broadcast(known_digests(spark)) if catalogue is None else catalogue
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("text_key", F.xxhash64("text"))
    # Spellings never cross a line border, so the lines of the spelled document are the spelled lines.
    rows_spelled = rows.where("text is not null").withColumn("spelled", _spelled(F.col("text")))
    none = F.array().cast("array<struct<part:int,body:string>>")
    whole = F.array(F.struct(F.lit(0).alias("part"), F.col("spelled").alias("body")))
    lines = F.transform(F.split("spelled", "\n"), lambda x, i: F.struct((i + 1).alias("part"), x.alias("body")))
    blocks = F.transform(F.split("text", "\n[ \t]*\n"), lambda x, i: F.struct((-1 - i).alias("part"), _spelled(x).alias("body")))
    inner = F.when(F.contains("text", F.lit("\n")), F.concat(lines, F.when(F.col("text").rlike("\n[ \t]*\n"), blocks).otherwise(none))).otherwise(none)
    several = F.when(F.contains("text", F.lit("\n")), _paragraph_runs(F.col("spelled"), paragraphs)).otherwise(none)
    digests = F.concat(
        F.transform(F.concat(whole, inner), lambda t: F.struct(t["part"].alias("part"), F.sha2(_spaced(t["body"]), 256).alias("digest"))),
        F.transform(several, lambda t: F.struct(t["part"].alias("part"), F.sha2(t["body"], 256).alias("digest"))),
    )
    hits = rows_spelled.select("doc_id", "text_key", F.explode(digests).alias("t")).select("doc_id", "text_key", "t.part", "t.digest").join(known, "digest")
    per_doc = hits.groupBy(F.col("doc_id").alias("hit_id"), F.col("text_key").alias("hit_key")).agg(
        F.countDistinct("part").alias("n_texts"),
        F.array_join(F.sort_array(F.collect_set("license")), ",").alias("licenses"),
        F.min(F.when(F.col("part") == 0, F.col("license"))).alias("whole_license"),
    )
    joined = rows.select("doc_id", "text_key").join(per_doc, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("text_key") == F.col("hit_key")), "left")
    return joined.select("doc_id", F.coalesce("n_texts", F.lit(0)).cast("long").alias("n_texts"), F.coalesce("licenses", F.lit("")).alias("licenses"), F.coalesce("whole_license", F.lit("")).alias("whole_license"))


def _quoted(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def _sql_canonical(text: str) -> str:
    out = f"regexp_replace(translate({text}, '{_UPPER}', '{_LOWER}'), {_quoted(SQL_COPYRIGHT_LINE)}, '', 'g')"
    for written, form in SPELLINGS:
        out = f"replace({out}, {_quoted(written)}, {_quoted(form)})"
    return f"trim(regexp_replace({out}, {_quoted(NOT_WORD)}, ' ', 'g'))"


def scan_sql() -> str:
    """The same scan as DuckDB SQL."""
    rows = ", ".join(f"({_quoted(k)}, {_quoted(t)})" for k, t in KNOWN)
    return f"""
WITH known AS (SELECT DISTINCT sha256({_sql_canonical('text')}) AS digest, license FROM (VALUES {rows}) v(license, text)),
parts AS (
  SELECT doc_id, 0 AS part, text AS body FROM documents WHERE text IS NOT NULL
  UNION ALL
  SELECT doc_id, i, string_split(text, chr(10))[i] FROM (SELECT doc_id, text, unnest(generate_series(1, len(string_split(text, chr(10))))) AS i FROM documents WHERE contains(text, chr(10)))
  UNION ALL
  SELECT doc_id, -i, regexp_split_to_array(text, '\\n[ \\t]*\\n')[i] FROM (SELECT doc_id, text, unnest(generate_series(1, len(regexp_split_to_array(text, '\\n[ \\t]*\\n')))) AS i FROM documents WHERE regexp_matches(text, '\\n[ \\t]*\\n'))
),
hits AS (SELECT doc_id, part, license FROM (SELECT doc_id, part, sha256({_sql_canonical('body')}) AS digest FROM parts) JOIN known USING (digest)),
per_doc AS (SELECT doc_id, count(DISTINCT part) AS n, string_agg(DISTINCT license, ',' ORDER BY license) AS licenses, min(license) FILTER (WHERE part = 0) AS whole FROM hits GROUP BY doc_id)
SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_texts, coalesce(licenses, '') AS licenses, coalesce(whole, '') AS whole_license
FROM documents LEFT JOIN per_doc USING (doc_id)
"""
