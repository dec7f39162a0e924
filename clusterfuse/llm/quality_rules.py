"""Quality rules as a learned decision list.

Statistics of each text are Spark expressions. From a bounded sample of labelled documents, sequential covering grows
conjunctions of thresholds by information gain, prunes each on held-back rows, and keeps those that are precise enough
there; the list is emitted as one ordered conditional expression, so judging a text is a projection in the JVM.

Null and empty texts have no words and fail the base rule. Repeated rows are judged one by one; an empty table gives an
empty result; without labels of both kinds the list is empty and the base rule alone decides. Columns other than doc_id
and text are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import struct_of
from .common import BLANK, blank_words, let, table, unused

WINDOW = 8
SYMBOLS = r"[#*$%&|<>]"
#: Labelled rows that a list is learned from, at most; the first ones by hash of doc_id.
MAX_LABELLED = 6000
MAX_RULES, MAX_TERMS, CUTS = 12, 4, 24
#: Share of low-quality documents among the held-back ones that a rule meets.
PRECISION = 0.9
FEATURES = ["n_words", "word_length", "symbol_share", "dup_line_share", "repeat_share", "distinct_share", "same_next_share", "words_a_line"]


def _repeated(h: Column) -> Column:
    """Words in 8-word windows that stand twice or more in the text, from the array of word hashes."""
    windows = F.when(F.size(h) >= WINDOW, F.transform(F.sequence(F.lit(1), F.size(h) - (WINDOW - 1)), lambda i: F.xxhash64(*[F.element_at(h, i + d) for d in range(WINDOW)]))).otherwise(F.array().cast("array<bigint>"))

    def covered(win: Column) -> Column:
        # windows sorted by hash and place: equal neighbours are repeats
        by_hash = F.sort_array(F.transform(win, lambda g, i: F.struct(g.alias("g"), i.alias("i"))))
        none = F.struct(F.lit(0).cast("bigint").alias("g"), F.lit(-1).alias("i"))

        def places(s: Column) -> Column:
            twin = F.zip_with(F.slice(F.concat(F.array(none), s), 1, F.size(s)), s, lambda a, b: (a["i"] >= 0) & (a["g"] == b["g"]))

            def kept(t: Column) -> Column:
                follows = F.concat(F.slice(t, 2, F.size(t)), F.array(F.lit(False)))
                flags = F.zip_with(t, follows, lambda a, b: a | b)
                return F.transform(F.filter(F.zip_with(s, flags, lambda x, f: F.when(f, x["i"])), lambda i: i.isNotNull()), lambda i: i)

            return F.sort_array(let(twin, kept))

        start = F.struct(F.lit(-WINDOW).alias("p"), F.lit(0).alias("n"))
        return F.aggregate(let(by_hash, places), start, lambda a, p: F.struct(p.alias("p"), (a["n"] + F.least(p - a["p"], F.lit(WINDOW))).alias("n")))["n"]

    return let(windows, lambda win: F.when(F.size(F.array_distinct(win)) == F.size(win), F.lit(0)).otherwise(covered(win)))


def statistics(text: Column) -> Column:
    """A struct of the counts that the base rule and the list use; no helper column meets the caller's."""
    whole = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(whole, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    of_lines = let(lines, lambda a: struct_of(n=F.size(a), dup=F.size(a) - F.size(F.array_distinct(a))))

    def same_next(h: Column) -> Column:
        start = struct_of(p=F.lit(None).cast("bigint"), n=F.lit(0))
        return F.aggregate(h, start, lambda a, x: struct_of(p=x, n=a["n"] + x.eqNullSafe(a["p"]).cast("int")))["n"]

    def of_words(w: Column) -> Column:
        hashed = let(F.transform(w, lambda x: F.xxhash64(x)), lambda h: struct_of(repeat=_repeated(h), distinct=F.size(F.array_distinct(h)), same=same_next(h)))
        return struct_of(n=F.size(w), chars=F.char_length(F.array_join(w, "")), h=hashed)

    def all_of(c: Column) -> Column:
        w, l, symbols = c["w"], c["l"], c["symbols"]
        n, one = w["n"].cast("double"), F.greatest(w["n"].cast("double"), F.lit(1.0))
        per_line = F.greatest(l["n"].cast("double"), F.lit(1.0))
        return struct_of(
            n_words_=w["n"].cast("long"),
            word_chars=w["chars"].cast("long"),
            n_symbols=symbols.cast("long"),
            n_dup_lines=l["dup"].cast("long"),
            n_repeat_words=w["h"]["repeat"].cast("long"),
            n_words=n,
            word_length=w["chars"] / one,
            symbol_share=symbols / one,
            dup_line_share=l["dup"] / per_line,
            repeat_share=w["h"]["repeat"] / one,
            distinct_share=w["h"]["distinct"] / one,
            same_next_share=w["h"]["same"] / one,
            words_a_line=n / per_line,
        )

    return let(struct_of(w=let(blank_words(text), of_words), l=of_lines, symbols=F.regexp_count(whole, F.lit(SYMBOLS))), all_of)


@dataclass(frozen=True)
class Rule:
    """Thresholds that all hold; terms are (feature, '<=' or '>', cut)."""

    terms: tuple[tuple[str, str, float], ...]

    def meets(self, row: dict) -> bool:
        return all(row[f] <= c if op == "<=" else row[f] > c for f, op, c in self.terms)

    def column(self, of: Column) -> Column:
        out = F.lit(True)
        for f, op, c in self.terms:
            out = out & (of[f] <= c if op == "<=" else of[f] > c)
        return out

    def __str__(self) -> str:
        return " and ".join(f"{f} {op} {c:.4g}" for f, op, c in self.terms)


def _counts(rows: list[dict], terms) -> tuple[int, int]:
    met = [r["low"] for r in rows if Rule(tuple(terms)).meets(r)]
    return sum(met), len(met) - sum(met)


def _settled(terms: list, rows: list[dict]) -> list:
    """Each cut moved to the middle of the gap between the low rows that the rule meets (but for the nearest 5 %) and the clean rows that the term keeps out."""
    terms = list(terms)
    for k, (f, op, c) in enumerate(terms):
        near = [r for r in rows if Rule(tuple(t for i, t in enumerate(terms) if i != k)).meets(r)]
        inside = sorted(r[f] for r in near if r["low"] and Rule((terms[k],)).meets(r))
        outside = [r[f] for r in near if not r["low"] and not Rule((terms[k],)).meets(r)]
        if inside and outside:
            edge, wall = (inside[len(inside) // 20], max(outside)) if op == ">" else (inside[-1 - len(inside) // 20], min(outside))
            terms[k] = (f, op, (edge + wall) / 2)
    return terms


def learn(rows: list[dict]) -> list[Rule]:
    """Sequential covering over rows of FEATURES and ``low`` (True: low quality)."""
    grow, prune = [r for i, r in enumerate(rows) if i % 3], [r for i, r in enumerate(rows) if i % 3 == 0]
    if not any(r["low"] for r in rows) or all(r["low"] for r in rows):
        return []
    cuts = {}
    for f in FEATURES:
        of_low, of_all = sorted(r[f] for r in grow if r["low"]), sorted(r[f] for r in grow)
        cuts[f] = sorted({s[min(len(s) - 1, len(s) * k // CUTS)] for s in (of_low, of_all) if s for k in range(1, CUTS)})
    rules: list[Rule] = []
    left, held = grow, prune
    while len(rules) < MAX_RULES and any(r["low"] for r in left):
        terms: list = []
        cover = left
        while len(terms) < MAX_TERMS and any(not r["low"] for r in cover):
            p0, n0 = sum(r["low"] for r in cover), sum(not r["low"] for r in cover)
            base, best = math.log2(p0 / (p0 + n0)), (0.0, None)
            for f in FEATURES:
                for c in cuts[f]:
                    above = [r["low"] for r in cover if r[f] > c]
                    pa, na = sum(above), len(above) - sum(above)
                    for op, p, n in ((">", pa, na), ("<=", p0 - pa, n0 - na)):
                        if p and (gain := p * (math.log2(p / (p + n)) - base)) > best[0]:
                            best = (gain, (f, op, c))
            if best[1] is None:
                break
            terms.append(best[1])
            cover = [r for r in cover if Rule((best[1],)).meets(r)]
        if not terms:
            break
        worth = lambda t: (lambda p, n: (p - n) / max(p + n, 1))(*_counts(held, t))
        while len(terms) > 1 and worth(terms[:-1]) >= worth(terms):
            terms = terms[:-1]
        terms = _settled(terms, left)
        p, n = _counts(held, terms)
        rule = Rule(tuple(terms))
        if p + n and p / (p + n) >= PRECISION:
            rules.append(rule)
        rest = [r for r in left if not rule.meets(r)]
        left, held = (rest if len(rest) < len(left) else []), [r for r in held if not rule.meets(r)]
    return rules


def learn_from(docs: DataFrame, labels: DataFrame, limit: int = MAX_LABELLED) -> list[Rule]:
    """The list learned from at most ``limit`` labelled documents (labels: doc_id, quality 0 or 1)."""
    sample = labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", "quality").orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(limit)
    known = docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id")  # bounded by ``limit``
    found = known.select("doc_id", (F.col("quality") == 0).alias("low"), statistics(F.col("text")).alias("q")).select("doc_id", "low", "q.*").orderBy(F.xxhash64("doc_id"), "doc_id", "low", *FEATURES).limit(limit).collect()
    return learn([{k: r[k] for k in [*FEATURES, "low"]} for r in sorted(found, key=lambda r: (hash_place(r["doc_id"]), r["low"]))])


def hash_place(doc_id: int) -> int:
    """A fixed scatter of ids, so that growing and pruning rows are mixed alike in every run."""
    return (int(doc_id) * 0x9E3779B97F4A7C15) % (1 << 64)


def list_column(rules: list[Rule], of: Column) -> Column:
    """Place of the first rule that rejects (from 1), 0 if none does: one ordered conditional expression."""
    if not rules:
        return F.lit(0)
    out = F.when(rules[0].column(of), 1)
    for i, rule in enumerate(rules[1:], 2):
        out = out.when(rule.column(of), i)
    return out.otherwise(0)


def verdict(text: Column, rules: list[Rule]) -> Column:
    """A struct: q (statistics), base_failed, rule (place of the first that rejects, 0: none), kept."""

    def judge(q: Column) -> Column:
        failed = (q["n_words_"] < 20) | (100 * q["n_repeat_words"] > 30 * q["n_words_"])
        rule = list_column(rules, q)
        return struct_of(q=q, base_failed=failed, rule=rule, kept=~failed & (rule == 0))

    return let(statistics(text), judge)


def judged(docs: DataFrame, rules: list[Rule], name: str = "verdict") -> DataFrame:
    """``docs`` with one more column ``name``, the verdict; a caller's column of that name is an error, not overwritten."""
    if unused(docs.columns, name) != name:
        raise ValueError(f"there is a column {name} already")
    return docs.withColumn(name, verdict(F.col("text"), rules))


def kept(docs: DataFrame, rules: list[Rule]) -> DataFrame:
    """The rows of ``docs`` that the base rule and the list keep, with the caller's columns alone."""
    name = unused(docs.columns, "verdict")
    return docs.withColumn(name, verdict(F.col("text"), rules)).filter(F.col(name)["kept"]).drop(name)


def query(spark, sf_dir):
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    out = judged(docs, learn_from(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))
    v, q = F.col("verdict"), F.col("verdict.q")
    return out.select("doc_id", q["n_words_"].alias("n_words"), *[q[c].alias(c) for c in ("word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], v["base_failed"].alias("base_failed"), v["kept"].alias("kept"), v["rule"].alias("rule"))


def base_query(spark, sf_dir):
    """The columns of the query that labels take no part in."""
    return query(spark, sf_dir).drop("kept", "rule")


BASE_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, list_filter(string_split_regex(coalesce(text, ''), '{BLANK}'), lambda x: x <> '') AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM documents),
g AS (SELECT doc_id, i, array_to_string(w[i:i + {WINDOW - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - {WINDOW - 2})) AS i FROM d WHERE len(w) >= {WINDOW})),
again AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM g) WHERE c > 1),
r AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + {WINDOW})) AS p FROM again) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(len(regexp_extract_all(t, '{SYMBOLS}')) AS BIGINT) AS n_symbols,
  CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words, len(w) < 20 OR 100 * coalesce(n, 0) > 30 * len(w) AS base_failed
FROM d LEFT JOIN r USING (doc_id)
"""
