"""Licence detection by diagonal voting.

Every rolling word k-gram of a text is hashed and joined to the positions of the same hash in the templates. A match at
text word i and template word j votes for diagonal i - j; a template that stands in the text puts its votes on one
diagonal, and inserted or deleted words move the rest to a neighbouring one. Votes are added up by diagonal,
neighbouring diagonals are merged, and each merged span is verified by the share of template words that its votes cover.

Phrases (two-grams) count only when all their grams lie on one diagonal, which is an exact occurrence; licence texts
(four-grams) need ``SHARE`` of their words. Null and empty texts have no words and no labels; repeated rows are judged
one by one; an empty table gives an empty result; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import LOWER, UPPER, let, plain_words, store, table

# Phrases that name a licence, and opening or operative passages of well-known licence texts.
BASE_PHRASES = [("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl")]
MORE_PHRASES = [
    ("cc by nc", "cc-by-nc"),
    ("cc by sa", "cc-by-sa"),
    ("cc by nd", "cc-by-nd"),
    ("creative commons attribution", "cc-by"),
    ("bsd license", "bsd"),
    ("mozilla public license", "mpl"),
    ("lesser general public license", "lgpl"),
    ("affero general public license", "agpl"),
    ("eclipse public license", "epl"),
    ("isc license", "isc"),
]
TEXTS = [
    (
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so",
    ),
    (
        "apache",
        "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license",
    ),
    (
        "gpl",
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    ),
    (
        "bsd",
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    ),
    (
        "isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    ),
]

PHRASE_K, TEXT_K = 2, 4
#: A merged span of a licence text is accepted from this share of template words on.
SHARE = 0.6
#: Diagonals at most so many words apart are one span.
MERGE = 8


def _grams(words: Column, k: int) -> Column:
    """Hashes of the k-grams of an array of words, in order."""
    at = lambda i: [F.element_at(words, i + d) for d in range(1, k + 1)]
    return F.when(F.size(words) >= k, F.transform(F.sequence(F.lit(0), F.size(words) - k), lambda i: F.xxhash64(F.lit(k), *at(i)))).otherwise(F.array().cast("array<bigint>"))


def templates(spark) -> DataFrame:
    """Gram positions of all templates: template, label, base, k, n_grams, n_template, t_pos, gram."""
    rows = [(t, label, k, base, text) for t, (label, k, base, text) in enumerate([*((l, PHRASE_K, True, p) for p, l in BASE_PHRASES), *((l, PHRASE_K, False, p) for p, l in MORE_PHRASES), *((l, TEXT_K, False, t) for l, t in TEXTS)])]
    df = spark.createDataFrame(rows, "template int, label string, k int, base boolean, body string").withColumn("words", plain_words(F.col("body")))
    grams = F.when(F.col("k") == PHRASE_K, let(F.col("words"), lambda w: _grams(w, PHRASE_K))).otherwise(let(F.col("words"), lambda w: _grams(w, TEXT_K)))
    df = df.select("template", "label", "base", "k", F.size("words").alias("n_template"), grams.alias("grams"))
    return df.select("template", "label", "base", "k", "n_template", F.size("grams").alias("n_grams"), F.posexplode("grams").alias("t_pos", "gram"))


def license_spans(docs: DataFrame) -> DataFrame:
    """Verified spans, one row each: row_key, doc_id, n_words, label, base, exact, first_word, last_word, share.

    A document has at least one row; without spans it is one with a null label. row_key tells repeated rows apart."""
    spark = docs.sparkSession
    # element 0 is a mark that meets a template row of its own, so every document survives the join; then the two-grams, then the four-grams
    mark = F.xxhash64(F.lit("document"))
    grams = let(plain_words(F.col("text")), lambda w: F.struct(F.size(w).alias("n"), F.concat(F.array(mark), _grams(w, PHRASE_K), _grams(w, TEXT_K)).alias("g")))
    held = docs.select(F.monotonically_increasing_id().alias("row_key"), "doc_id", grams.alias("x")).select("row_key", "doc_id", F.col("x.n").alias("n_words"), F.posexplode("x.g").alias("at", "gram"))
    plain = templates(spark)
    marked = spark.range(1).select(F.lit(-1).alias("template"), F.lit(None).cast("string").alias("label"), F.lit(False).alias("base"), F.lit(0).alias("k"), F.lit(0).alias("n_template"), F.lit(1).alias("n_grams"), F.lit(0).alias("t_pos"), mark.alias("gram"))
    # the templates are constants of this module: a few hundred rows
    hit = held.join(F.broadcast(plain.unionByName(marked)), "gram")
    two = F.greatest(F.col("n_words") - (PHRASE_K - 1), F.lit(0))
    start = F.when(F.col("k") == 0, 0).when(F.col("k") == PHRASE_K, F.col("at") - 1).otherwise(F.col("at") - 1 - two)
    votes = hit.withColumn("start", start).withColumn("diagonal", F.col("start") - F.col("t_pos"))
    by = ["row_key", "doc_id", "n_words", "template", "label", "base", "k", "n_template", "n_grams"]
    summed = votes.groupBy(*by, "diagonal").agg(F.count(F.lit(1)).alias("votes"), F.min("start").alias("lo"), F.max("start").alias("hi"), F.collect_set("t_pos").alias("met"))
    # phrases and spans both read them: a small table, so that texts are split and hashed once
    diagonals = store(summed, "diagonals")
    phrases = diagonals.filter((F.col("k") <= PHRASE_K) & (F.col("votes") == F.col("n_grams")))
    exact = phrases.select("row_key", "doc_id", "n_words", "label", "base", (F.col("k") == PHRASE_K).alias("exact"), F.col("diagonal").alias("first_word"), (F.col("diagonal") + F.col("n_template") - 1).alias("last_word"), F.lit(1.0).alias("share"))
    whole = Window.partitionBy("row_key", "template").orderBy("diagonal")
    gap = F.col("diagonal") - F.lag("diagonal").over(whole)
    spans = diagonals.filter(F.col("k") == TEXT_K).withColumn("new", F.coalesce((gap > MERGE).cast("int"), F.lit(1))).withColumn("span", F.sum("new").over(whole))
    spans = spans.groupBy(*by, "span").agg(F.min("lo").alias("first_word"), (F.max("hi") + TEXT_K - 1).alias("last_word"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("met")))).alias("met"))
    # template words under the grams met: a gram adds k words less those that the one before it has
    covered = F.aggregate("met", F.struct(F.lit(-TEXT_K).alias("p"), F.lit(0).alias("n")), lambda a, p: F.struct(p.alias("p"), (a["n"] + F.least(p - a["p"], F.lit(TEXT_K))).alias("n")))["n"]
    spans = spans.withColumn("share", covered / F.col("n_template")).filter(F.col("share") >= SHARE)
    return exact.unionByName(spans.select("row_key", "doc_id", "n_words", "label", "base", F.lit(False).alias("exact"), "first_word", "last_word", "share"))


def license_labels(docs: DataFrame) -> DataFrame:
    """One row for each document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    on = F.col("base")
    joined = lambda c: F.concat_ws(",", F.array_sort(F.collect_set(c)))
    out = license_spans(docs).groupBy("row_key").agg(
        F.first("doc_id").alias("doc_id"),
        F.max("n_words").cast("long").alias("n_words"),
        F.count_if(on).alias("n_base"),
        F.min(F.when(on, F.col("first_word"))).cast("long").alias("first_word"),
        F.max(F.when(on, F.col("first_word"))).cast("long").alias("last_word"),
        joined(F.when(on, F.col("label"))).alias("base_labels"),
        joined(F.col("label")).alias("labels"),
        F.coalesce(F.max(F.when(F.col("label").isNotNull(), F.col("share"))), F.lit(0.0)).alias("score"),
    )
    return out.drop("row_key")


def query(spark, sf_dir):
    return license_labels(table(spark, sf_dir, "documents", "doc_id", "text"))


_WORDS = rf"list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"
_TEMPLATES = ", ".join(f"({n}, '{label}', {str(base).lower()}, {k}, string_split('{body}', ' '))" for n, (label, base, k, body) in enumerate([*((l, True, PHRASE_K, p) for p, l in BASE_PHRASES), *((l, False, PHRASE_K, p) for p, l in MORE_PHRASES), *((l, False, TEXT_K, t) for l, t in TEXTS)]))
#: From the definition: phrases are compared word by word, k-grams are texts and not hashes.
ORACLE_SQL = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
t(template, label, base, k, tw) AS (VALUES {_TEMPLATES}),
two AS (SELECT doc_id, w, unnest(range(1, len(w))) AS i FROM d),
phrase AS (SELECT doc_id, label, base, i - 1 AS place, 1.0::DOUBLE AS share FROM two JOIN t ON t.k = {PHRASE_K} AND w[i] = tw[1] AND w[i + 1] = tw[2] WHERE w[i:i + len(tw) - 1] = tw),
dg AS (SELECT doc_id, i, array_to_string(w[i:i + {TEXT_K - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - {TEXT_K - 2})) AS i FROM d)),
tg AS (SELECT template, label, base, len(tw) AS size, j, array_to_string(tw[j:j + {TEXT_K - 1}], ' ') AS g FROM (SELECT *, unnest(range(1, len(tw) - {TEXT_K - 2})) AS j FROM t WHERE k = {TEXT_K})),
vote AS (SELECT doc_id, template, label, base, size, i - j AS diagonal, i, j FROM dg JOIN tg USING (g)),
lines AS (SELECT DISTINCT doc_id, template, diagonal FROM vote),
fresh AS (SELECT *, CASE WHEN diagonal - lag(diagonal) OVER (PARTITION BY doc_id, template ORDER BY diagonal) <= {MERGE} THEN 0 ELSE 1 END AS new FROM lines),
spans AS (SELECT doc_id, template, diagonal, sum(new) OVER (PARTITION BY doc_id, template ORDER BY diagonal ROWS UNBOUNDED PRECEDING) AS span FROM fresh),
under AS (SELECT DISTINCT doc_id, template, span, label, base, size, unnest(range(j, j + {TEXT_K})) AS word FROM vote JOIN spans USING (doc_id, template, diagonal)),
body AS (SELECT doc_id, label, base, count(*) * 1.0::DOUBLE / size AS share FROM under GROUP BY doc_id, template, span, label, base, size HAVING count(*) * 1.0::DOUBLE / size >= {SHARE}),
every AS (SELECT doc_id, label, base, place, share FROM phrase UNION ALL SELECT doc_id, label, base, NULL, share FROM body)
SELECT d.doc_id, CAST(len(any_value(d.w)) AS BIGINT) AS n_words, CAST(count(*) FILTER (WHERE base) AS BIGINT) AS n_base,
  CAST(min(place) FILTER (WHERE base) AS BIGINT) AS first_word, CAST(max(place) FILTER (WHERE base) AS BIGINT) AS last_word,
  coalesce(string_agg(DISTINCT label, ',' ORDER BY label) FILTER (WHERE base), '') AS base_labels, coalesce(string_agg(DISTINCT label, ',' ORDER BY label), '') AS labels, coalesce(max(share), 0.0::DOUBLE) AS score
FROM d LEFT JOIN every USING (doc_id) GROUP BY d.doc_id
"""
