"""Benchmark decontamination with a distributed positional inverted index.

The index is a table of postings (row_key, pos, code): one for each place of a training text that holds a word of the
benchmark's vocabulary (other words can't take part in a match), and one mark at pos 0 for each document with its length.
A phrase is looked up from its rarest words: the postings of the rarest give candidate starts (place less offset), the
list of the second rarest is intersected with them at its own offset, and only what is left meets the lists of the other
words. What stays has every word at its place: exact occurrences. ``proximity_matches`` finds items whose rarest words
lie close together in any order, which the result counts beside the exact phrases.

Benchmark tables are broadcast only when a count shows that they have at most ``SMALL`` rows; otherwise Spark joins them
like any table. Null and empty texts have no words: such documents are clean, such items have no window. Repeated rows
are judged one by one (row_key tells them apart); items with one text count each. Empty tables give no hits or no rows.
Columns other than the ids and texts are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import LOWER, UPPER, let, plain_words, store, table, text_key, without_texts

WINDOW = 10
SMALL = 500_000
MARK = "\x00"
#: Proximity: so many of an item's rarest words within so many words of a text.
NEAR_TERMS, NEAR_SPAN = 3, 20


def _small(df: DataFrame) -> DataFrame:
    """Broadcast ``df`` if its count allows that."""
    return F.broadcast(df) if df.limit(SMALL + 1).count() <= SMALL else df


def benchmark_windows(items: DataFrame, window: int = WINDOW) -> DataFrame:
    """Distinct windows of ``items`` (item_id, text): wid, terms, item_ids."""
    held = items.select("item_id", plain_words(F.col("text")).alias("w")).filter(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - (window - 1), F.lit(1)))
    each = held.select("item_id", F.explode(let(F.col("w"), lambda w: F.transform(starts, lambda s: F.slice(w, s, window)))).alias("terms"))
    grouped = each.groupBy("terms").agg(F.collect_set("item_id").alias("item_ids"))
    return grouped.select(F.xxhash64("terms").alias("wid"), "terms", "item_ids")


def build_index(docs: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """Postings of ``docs`` (doc_id, text) for the words of ``vocabulary`` (term, code from 1); code 0 marks documents."""
    with_mark = vocabulary.unionByName(docs.sparkSession.range(1).select(F.lit(MARK).alias("term"), F.lit(0).cast("long").alias("code")))
    words = let(plain_words(F.col("text")), lambda w: F.struct(F.size(w).alias("n"), F.concat(F.array(F.lit(MARK)), w).alias("w")))
    places = docs.select(F.monotonically_increasing_id().alias("row_key"), "doc_id", words.alias("x")).select("row_key", "doc_id", F.col("x.n").alias("n"), F.posexplode("x.w").alias("pos", "term"))
    at_mark = lambda c: F.when(F.col("code") == 0, F.col(c))
    return store(places.join(_small(with_mark), "term").select("row_key", "pos", "code", at_mark("doc_id").alias("doc_id"), at_mark("n").cast("long").alias("n_words")), "postings")


def vocabulary_of(windows: DataFrame) -> DataFrame:
    """Distinct words of the windows (term) with a ``code`` from 1; codes are unique, not gapless, and given without gathering the words."""
    terms = windows.select(F.explode("terms").alias("term")).distinct()
    return store(terms.withColumn("code", F.monotonically_increasing_id() + 1), "vocabulary")


def probe_order(windows: DataFrame, vocabulary: DataFrame, index: DataFrame) -> DataFrame:
    """wid, size, item_ids and ``by_rarity``: (count, code, offset) of each word, rarest first; windows with a word that never occurs go."""
    counts = store(index.filter("code > 0").groupBy("code").agg(F.count(F.lit(1)).alias("n")), "term-counts")
    parts = windows.select("wid", F.size("terms").alias("size"), "item_ids", F.posexplode("terms").alias("off", "term")).join(_small(vocabulary), "term")
    known = parts.join(_small(counts), "code")
    ranked = known.groupBy("wid", "size").agg(F.sort_array(F.collect_list(F.struct("n", "code", "off"))).alias("by_rarity"), F.first("item_ids").alias("item_ids"))
    return store(ranked.filter(F.size("by_rarity") == F.col("size")), "probes")


def phrase_matches(index: DataFrame, probes: DataFrame) -> DataFrame:
    """Exact occurrences: row_key, wid, size, start (words from 1)."""
    nth = lambda k: F.get("by_rarity", F.lit(k))
    rarest = probes.select("wid", "size", nth(0)["code"].alias("code"), nth(0)["off"].alias("off"), nth(1)["code"].alias("code2"), nth(1)["off"].alias("off2"))
    postings = index.filter("code > 0").select("row_key", "pos", "code")
    starts = postings.join(_small(rarest), "code").withColumn("start", F.col("pos") - F.col("off")).filter("start >= 1")
    alone = starts.filter("code2 is null").select("row_key", "wid", "size", "start")
    second = postings.join(_small(rarest.filter("code2 is not null").select(F.col("code2").alias("code")).distinct()), "code", "left_semi")
    asked = starts.filter("code2 is not null").select("row_key", "wid", "size", "start", F.col("code2").alias("code"), (F.col("start") + F.col("off2")).alias("pos"))
    two = store(asked.join(second, ["row_key", "pos", "code"]).select("row_key", "wid", "size", "start").union(alone), "two-words")
    # only documents that still have a candidate take part in the rest; stored, so that Spark knows how many they are
    holders = store(two.select("row_key").distinct(), "holders")
    rest = probes.select("wid", F.explode(F.slice("by_rarity", 3, WINDOW)).alias("r")).select("wid", F.col("r.code").alias("code"), F.col("r.off").alias("off"))
    asked = two.filter("size > 2").join(_small(rest), "wid").select("row_key", "wid", "size", "start", "code", (F.col("start") + F.col("off")).alias("pos"))
    met = asked.join(postings.join(holders, "row_key", "left_semi"), ["row_key", "pos", "code"])
    whole = met.groupBy("row_key", "wid", "size", "start").agg(F.count(F.lit(1)).alias("met")).filter(F.col("met") == F.col("size") - 2).drop("met")
    return whole.union(two.filter("size <= 2"))


def proximity_matches(index: DataFrame, vocabulary: DataFrame, items: DataFrame, terms: int = NEAR_TERMS, span: int = NEAR_SPAN) -> DataFrame:
    """Items whose ``terms`` rarest distinct words (of those that occur; ties: the smaller word) lie within ``span`` words of a text, in any order.

    row_key, item_id, first_pos. An item with fewer such words needs all of them; one without any matches nowhere."""
    counts = store(index.filter("code > 0").groupBy("code").agg(F.count(F.lit(1)).alias("n")), "term-counts")
    words = items.select("item_id", F.explode(F.array_distinct(plain_words(F.col("text")))).alias("term")).join(_small(vocabulary), "term").join(_small(counts), "code")
    order = Window.partitionBy("item_id").orderBy("n", "term")
    ranked = words.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= terms)
    rare = store(ranked.withColumn("k", F.count(F.lit(1)).over(Window.partitionBy("item_id"))).select("item_id", "code", "k"), "rare-words")
    near = index.filter("code > 0").select("row_key", "pos", "code").join(_small(rare), "code")
    # a place belongs to its own stretch and the one before it, so each span lies whole in one; a stretch has 2 * span places
    stretch = F.explode(F.array(F.floor(F.col("pos") / span), F.floor(F.col("pos") / span) - 1)).alias("stretch")
    held = near.select("row_key", "item_id", "k", "pos", "code", stretch).groupBy("row_key", "item_id", "k", "stretch").agg(F.sort_array(F.collect_set(F.struct("pos", "code"))).alias("at"))
    held = held.filter(F.size("at") >= F.col("k"))
    from_here = lambda e: F.size(F.array_distinct(F.transform(F.filter("at", lambda x: (x["pos"] >= e["pos"]) & (x["pos"] < e["pos"] + span)), lambda x: x["code"])))
    first = F.get(F.filter("at", lambda e: from_here(e) == F.col("k")), F.lit(0))["pos"]
    return held.select("row_key", "item_id", first.alias("first_pos")).filter("first_pos is not null").groupBy("row_key", "item_id").agg(F.min("first_pos").alias("first_pos"))


def contamination(docs: DataFrame, items: DataFrame) -> DataFrame:
    """One row for each document: row_key, doc_id, n_words, n_hit, n_items, items_sha256, contaminated; and n_near, near_sha256 of the items close by.

    Only exact phrases make a document contaminated."""
    windows = store(benchmark_windows(items), "windows")
    vocabulary = vocabulary_of(windows)
    index = build_index(docs, vocabulary)
    probes = probe_order(windows, vocabulary, index)
    found = store(phrase_matches(index, probes), "phrases")
    hit = found.select("row_key", F.explode(F.sequence("start", F.col("start") + F.col("size") - 1)).alias("pos")).distinct().groupBy("row_key").agg(F.count(F.lit(1)).alias("n_hit"))
    which = found.select("row_key", "wid").distinct().join(_small(probes.select("wid", "item_ids")), "wid")
    which = which.select("row_key", F.explode("item_ids").alias("item_id")).groupBy("row_key").agg(F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("ids"))
    close = proximity_matches(index, vocabulary, items).groupBy("row_key").agg(F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("near"))
    marks = index.filter("code = 0").select("row_key", "doc_id", "n_words")
    out = marks.join(hit, "row_key", "left").join(which, "row_key", "left").join(close, "row_key", "left")
    n = F.coalesce("n_hit", F.lit(0)).cast("long")
    ids, near = (F.coalesce(c, F.array().cast("array<string>")) for c in ("ids", "near"))
    digest = lambda of: F.sha2(F.array_join(of, ",").cast("binary"), 256)
    return out.select("row_key", "doc_id", "n_words", n.alias("n_hit"), F.size(ids).cast("long").alias("n_items"), digest(ids).alias("items_sha256"), (n > 0).alias("contaminated"), F.size(near).cast("long").alias("n_near"), digest(near).alias("near_sha256"))


def without_contaminated(docs: DataFrame, items: DataFrame) -> DataFrame:
    """The rows of ``docs``, with the caller's columns alone, whose text holds no window of ``items``."""
    texts = docs.select(F.struct(*text_key()).alias("doc_id"), "text")
    return without_texts(docs, contamination(texts, items).filter("contaminated").select("doc_id.*"))


def query(spark, sf_dir):
    return contamination(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text")).drop("row_key")


_WORDS = rf"list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"
ORACLE_SQL = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT item_id, {_WORDS} AS w FROM benchmark),
win AS (SELECT item_id, w[s:least(s + {WINDOW - 1}, len(w))] AS terms FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - {WINDOW - 2}, 2))) AS s FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT len(terms) AS k FROM win),
grams AS (SELECT doc_id, s, w[s:s + k - 1] AS terms, k FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS s FROM d, sizes WHERE len(w) >= k)),
occ AS (SELECT g.doc_id, g.s, g.k, win.item_id FROM grams g JOIN win ON win.terms = g.terms),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + k)) AS p FROM occ) GROUP BY doc_id),
ids AS (SELECT doc_id, list_sort(list(DISTINCT CAST(item_id AS VARCHAR))) AS l FROM occ GROUP BY doc_id),
post AS (SELECT doc_id, unnest(w) AS term, generate_subscripts(w, 1) AS pos FROM d),
cnt AS (SELECT term, count(*) AS n FROM post GROUP BY term),
rare AS (SELECT item_id, term, count(*) OVER (PARTITION BY item_id) AS k FROM (SELECT item_id, term, row_number() OVER (PARTITION BY item_id ORDER BY n, term) AS r
  FROM (SELECT DISTINCT item_id, unnest(w) AS term FROM b) JOIN cnt USING (term)) WHERE r <= {NEAR_TERMS}),
spot AS (SELECT doc_id, item_id, k, pos, term FROM post JOIN rare USING (term)),
met AS (SELECT DISTINCT doc_id, item_id FROM (SELECT x.doc_id, x.item_id, x.pos, x.k FROM spot x JOIN spot y ON x.doc_id = y.doc_id AND x.item_id = y.item_id AND y.pos BETWEEN x.pos AND x.pos + {NEAR_SPAN - 1}
  GROUP BY x.doc_id, x.item_id, x.pos, x.k HAVING count(DISTINCT y.term) = x.k)),
near AS (SELECT doc_id, list_sort(list(DISTINCT CAST(item_id AS VARCHAR))) AS m FROM met GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit,
  CAST(coalesce(len(l), 0) AS BIGINT) AS n_items, sha256(coalesce(array_to_string(l, ','), '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AS contaminated, CAST(coalesce(len(m), 0) AS BIGINT) AS n_near, sha256(coalesce(array_to_string(m, ','), '')) AS near_sha256
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN ids USING (doc_id) LEFT JOIN near USING (doc_id)
"""
