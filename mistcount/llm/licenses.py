"""License scans by diagonal voting, in DataFrame operations only.

All rolling two-word hashes of the texts are joined to the places of the same hashes in the license
templates, a fixed table that is broadcast; the joined words are compared as well, so a hit is exact.
A hit at word i of a text and word p of a template votes for the diagonal i - p. A phrase stands where
its diagonal has all its votes. A longer template may have lost or gained words: votes of neighbouring
diagonals are merged, and the span stands if enough of the template's places are hit within a length
that suits the template. Places are kept as bits of 64-bit masks, as many as a template needs, so templates
of any length are found: sentences and the whole texts of licenses.

A null text is the empty one: no words and no labels. Rows that repeat a doc_id and text get the same
result each; rows of one doc_id with other texts are kept apart. Very long texts are read whole; what is shuffled
is a row for each diagonal with a hit. Only doc_id and text are read, so other columns of any name do no harm.
Spans of equal share all count, so nothing hangs on ties. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

#: Phrases and their labels.
PHRASES = (
    ("gpl", "gnu general public license"),
    ("apache", "apache license"),
    ("cc-by", "cc by"),
    ("mit", "mit license"),
)
#: Sentences of public licenses, whose labels are the method's own.
SENTENCES = (
    ("apache-2.0", "licensed under the apache license version 2 0"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-sa", "licensed under cc by sa 4 0"),
    ("gpl-notice", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("gpl-3", "licensed under the gnu general public license version 3"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("lgpl", "gnu lesser general public license"),
    ("mit-grant", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("mit-release", "released under the mit license"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license"),
    ("unlicense", "this is free and unencumbered software released into the public domain"),
)
#: Whole texts of public licenses, without the line that names the holder.
TEXTS = (
    ("bsd-2-clause-text", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met 1 redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer 2 redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or consequential damages including but not limited to procurement of substitute goods or services loss of use data or profits or business interruption however caused and on any theory of liability whether in contract strict liability or tort including negligence or otherwise arising in any way out of the use of this software even if advised of the possibility of such damage"),
    ("isc-text", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or performance of this software"),
    ("mit-text", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software"),
    ("zlib-text", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions 1 the origin of this software must not be misrepresented you must not claim that you wrote the original software if you use this software in a product an acknowledgment in the product documentation would be appreciated but is not required 2 altered source versions must be plainly marked as such and must not be misrepresented as being the original software 3 this notice may not be removed or altered from any source distribution"),
)
#: Templates as (base, label, words); base ones need all their places on one diagonal.
TEMPLATES = tuple((base, label, phrase) for base, group in ((True, PHRASES), (False, SENTENCES), (False, TEXTS)) for label, phrase in group)
#: The label of a text's end: two empty words follow the last one, so its place is the number of words, and
#: every text has a hit.
END = "#"
#: Diagonals at most so far apart are one span; votes that a diagonal needs to be merged.
DRIFT, VOTES = 3, 2
#: Share of a template's places that a span must hit, and its greatest length by the template's.
COVER, STRETCH = 0.75, 2
#: Letters of either case, digits and all beyond ASCII.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def templates(spark: SparkSession, known: tuple[tuple[bool, str, str], ...] = TEMPLATES) -> DataFrame:
    """A row for each two-word place of each template: a fixed table of some hundred rows."""
    rows = []
    for base, label, phrase in known:
        words = phrase.split()
        rows += [(base, label, len(words) - 1, p, words[p], words[p + 1]) for p in range(len(words) - 1)]
    rows.append((True, END, 1, 0, "", ""))
    return spark.createDataFrame(rows, "base boolean, label string, places int, p int, t0 string, t1 string").withColumn("h", F.xxhash64("t0", "t1"))


def _small(word: Column) -> Column:
    """Lower case of A-Z only."""
    return F.translate(word, _UPPER, _LOWER)


def hits(docs: DataFrame, key: list[str], text: str, known: tuple[tuple[bool, str, str], ...] = TEMPLATES) -> DataFrame:
    """key, template, diagonal, part; the mask of the 64 places of that part that are hit, the first and last word, and the hits."""
    words = F.concat(F.regexp_extract_all(F.coalesce(F.col(text), F.lit("")), F.lit(WORD), F.lit(0)), F.array(F.lit(""), F.lit("")))
    pairs = docs.select(*key, words.alias("_w")).select(*key, F.posexplode(F.arrays_zip(F.col("_w").alias("a"), F.slice("_w", F.lit(2), F.size("_w")).alias("b"))).alias("i", "pair"))
    # lower() may change letters beyond ASCII too, so it only makes the hash; the words are compared with A-Z lowered
    grams = pairs.where(F.col("pair.b").isNotNull()).select(*key, "i", F.col("pair.a").alias("w0"), F.col("pair.b").alias("w1"), F.xxhash64(F.lower("pair.a"), F.lower("pair.b")).alias("h"))
    found = grams.join(F.broadcast(templates(docs.sparkSession, known)), "h").where((_small(F.col("w0")) == F.col("t0")) & (_small(F.col("w1")) == F.col("t1")))
    # masks make repeated rows count once
    by = [*key, "base", "label", "places", (F.col("i") - F.col("p")).alias("diagonal"), F.shiftright("p", 6).alias("part")]
    return found.groupBy(*by).agg(F.bit_or(F.expr("shiftleft(1L, p & 63)")).alias("mask"), F.min("i").alias("first"), (F.max("i") + 1).alias("last"), F.count("*").alias("rows"))


def spans(votes: DataFrame, key: list[str]) -> DataFrame:
    """Verified spans: key, base, label, first and last word, share of the template that is hit."""
    line = Window.partitionBy(*key, "base", "label").orderBy("diagonal")
    counted = votes.withColumn("_votes", F.sum(F.bit_count("mask")).over(line.rangeBetween(Window.currentRow, Window.currentRow)))
    fit = counted.where(F.when(F.col("base"), F.col("_votes") == F.col("places")).otherwise(F.col("_votes") >= F.least(F.lit(VOTES), F.col("places"))))
    apart = F.col("diagonal") - F.lag("diagonal").over(line) > DRIFT
    near = fit.withColumn("_new", F.coalesce(apart, F.lit(True)).cast("int"))
    near = near.withColumn("_span", F.when(F.col("base"), F.col("diagonal")).otherwise(F.sum("_new").over(line)))  # phrases are never merged
    by = [*key, "base", "label", "places", "_span"]
    ends = [F.min("first").alias("first"), F.max("last").alias("last"), F.max("rows").alias("rows")]
    parts = near.groupBy(*by, "part").agg(F.bit_or("mask").alias("mask"), *ends)
    merged = parts.groupBy(*by).agg((F.sum(F.bit_count("mask")) / F.col("places")).alias("share"), *ends)
    held = F.col("base") | ((F.col("share") >= COVER) & (F.col("last") - F.col("first") + 1 <= STRETCH * (F.col("places") + 1)))
    return merged.where(held).select(*key, "base", "label", "first", "last", "rows", "share")


def scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", known: tuple[tuple[bool, str, str], ...] = TEMPLATES) -> DataFrame:
    """One row for each row of docs: words, base places, their first and last word, labels, score."""
    keyed = docs.select(F.col(doc_id).alias("doc_id"), F.xxhash64(text).alias("_h"), F.col(text).alias("_text"))
    key = ["doc_id", "_h"]
    end, label = F.col("label") == END, F.col("label")
    base, named = F.col("base") & ~end, F.when(~end, label)
    by_doc = spans(hits(keyed, key, "_text", known), key).groupBy(*key).agg(
        F.max(F.when(end, F.col("first"))).cast("long").alias("n_words"), F.max(F.when(end, F.col("rows"))).alias("rows"), F.sum(base.cast("long")).alias("n_base"),
        F.min(F.when(base, F.col("first"))).cast("long").alias("first_word"), F.max(F.when(base, F.col("first"))).cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.collect_set(F.when(base, label))), ",").alias("base_labels"), F.array_join(F.array_sort(F.collect_set(named)), ",").alias("labels"),
        F.coalesce(F.max(F.when(~end, F.col("share"))), F.lit(0.0)).alias("score"),
    )
    # a row for each row of docs: the end was hit once in each
    return by_doc.withColumn("_row", F.explode(F.sequence(F.lit(1), F.col("rows")))).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")


def op3_license_scan(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score of every document."""
    return scan(table(spark, sf_dir, "documents").select("doc_id", "text"))


def _template_values() -> str:
    return ", ".join(f"({base}, '{label}', string_split('{phrase}', ' '))" for base, label, phrase in TEMPLATES)


OP3_SQL = rf"""
WITH t AS (SELECT * FROM (VALUES {_template_values()}) x(base, label, tw)),
tp AS (SELECT base, label, len(tw) - 1 AS places, p, tw[p + 1] AS t0, tw[p + 2] AS t1 FROM t, unnest(range(len(tw) - 1)) u(p)),
d AS (SELECT doc_id, coalesce(md5(text), '') AS k, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{WORD}') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, k, i, w[i + 1] AS w0, w[i + 2] AS w1 FROM d, unnest(range(greatest(len(w) - 1, 0))) u(i)),
h AS (SELECT doc_id, k, base, label, places, i - p AS diagonal, p, i FROM g JOIN tp ON w0 = t0 AND w1 = t1),
v AS (
  SELECT doc_id, k, base, label, places, diagonal, list(DISTINCT p) AS ps, min(i) AS a, max(i) + 1 AS z FROM h GROUP BY doc_id, k, base, label, places, diagonal
),
n AS (
  SELECT *, coalesce(CAST(diagonal - lag(diagonal) OVER o > {DRIFT} AS INTEGER), 1) AS fresh FROM v
  WHERE NOT base AND len(ps) >= least({VOTES}, places) WINDOW o AS (PARTITION BY doc_id, k, label ORDER BY diagonal)
),
m AS (SELECT *, sum(fresh) OVER (PARTITION BY doc_id, k, label ORDER BY diagonal) AS span FROM n),
f AS (
  SELECT doc_id, k, base, label, places, min(a) AS a, max(z) AS z, len(list_distinct(flatten(list(ps)))) AS hit FROM m GROUP BY doc_id, k, base, label, places, span
),
s AS (
  SELECT doc_id, k, base, label, a, 1.0::DOUBLE AS share FROM v WHERE base AND len(ps) = places
  UNION ALL
  SELECT doc_id, k, base, label, a, (hit / places)::DOUBLE AS share FROM f WHERE hit / places >= {COVER} AND z - a + 1 <= {STRETCH} * (places + 1)
),
r AS (
  SELECT doc_id, k, count(*) FILTER (WHERE base) AS n_base, min(a) FILTER (WHERE base) AS first_word, max(a) FILTER (WHERE base) AS last_word,
    string_agg(DISTINCT label, ',' ORDER BY label) FILTER (WHERE base) AS base_labels, string_agg(DISTINCT label, ',' ORDER BY label) AS labels, max(share) AS score
  FROM s GROUP BY doc_id, k
)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_base, 0) AS BIGINT) AS n_base, CAST(first_word AS BIGINT) AS first_word, CAST(last_word AS BIGINT) AS last_word,
  coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels, coalesce(score, 0.0)::DOUBLE AS score
FROM d LEFT JOIN r ON d.doc_id IS NOT DISTINCT FROM r.doc_id AND d.k = r.k
"""
