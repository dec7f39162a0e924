"""Registered queries of the engine, each beside the DuckDB SQL for the same rows.

The SQL is written from raw rows and plain determinants wherever it can be, so that it does not share formulas with the code.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..functions.deploy import ship
from ..operators import cliques, fuse, graph, measures, pairs, stats, tiles
from ..operators import summarize as S
from ..sources import exchange, scenarios, tables
from ..streaming import summaries
from . import experiment, surface
from .sql import BEST_PAIR, BRANDS, DISCS, FLAGS, MEASURE_SQL, MUTUAL_PAIRS, PAIRS, SCENARIO_K, SUPPLIERS, Z, all_measures, fused_rows, iterated, matrix_pairs, psi, psi1

CATALOG: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        CATALOG[name] = lambda spark, sf_dir: f(ship(spark), sf_dir)
        if sql:
            SQL[name] = sql
        return f

    return add


def queries():
    return dict(CATALOG)


def oracle_sql():
    return dict(SQL)


def r(c, k: int = 6) -> Column:
    """Rounded, with one kind of zero."""
    return F.round(F.col(c) if isinstance(c, str) else c, k) + F.lit(0.0)


def second(pairs_sql: str) -> str:
    """The CTEs of pairs once more, over k2 and ending in y2."""
    for name in ("pr", "x", "y"):
        pairs_sql = pairs_sql.replace(f"{name} AS (SELECT", f"{name}2 AS (SELECT").replace(f"FROM {name})", f"FROM {name}2)")
    return pairs_sql.replace("FROM k p JOIN k q", "FROM k2 p JOIN k2 q")


def flag_id() -> Column:
    return F.ascii("l_returnflag") * 1000 + F.ascii("l_linestatus")


def flags(spark, d, dim=2):
    return S.summarize_columns(scenarios.lineitem_z(spark, d, dim, ("l_returnflag", "l_linestatus")), flag_id(), [f"z{i + 1}" for i in range(dim)])


def suppliers(spark, d, dim=2):
    return S.summarize_columns(scenarios.lineitem_z(spark, d, dim, ("l_suppkey",)), F.col("l_suppkey"), [f"z{i + 1}" for i in range(dim)])


def brands(spark, d):
    return S.summarize_columns(tables.read_table(spark, d, "part", ["p_brand", "p_size", "p_retailprice"]), F.regexp_extract("p_brand", "([0-9]+)$", 1), ["p_size", "p_retailprice"])


def labels(spark, d, dim):
    return S.summarize_vectors(tables.read_table(spark, d, "embeddings", ["label", "embedding"]), F.col("label"), "embedding", dim)


def event_types(spark, d):
    return S.summarize_columns(tables.read_table(spark, d, "events", ["event_type", "value"]), F.ascii("event_type") * 1000 + F.length("event_type"), ["value"])


def disc_clusters(spark, d):
    return scenarios.discs(scenarios.lineitem_z(spark, d))


def stored(df: DataFrame, name: str = "clusters") -> DataFrame:
    return tables.store(df, name)


def flat2(df: DataFrame) -> DataFrame:
    at = F.element_at
    return df.select("cluster_id", "n", r(at("mean", 1)).alias("m1"), r(at("mean", 2)).alias("m2"), r(at("cov", 1)).alias("a"), r(at("cov", 2)).alias("b"), r(at("cov", 3)).alias("c"))


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.select(*[r(c).alias(c) if c in columns else F.col(c) for c in df.columns])


FLAT_SQL = "SELECT CAST(id AS BIGINT) AS cluster_id, CAST(n AS BIGINT) AS n, round(m1,6)+0.0 AS m1, round(m2,6)+0.0 AS m2, round(a,6)+0.0 AS a, round(b,6)+0.0 AS b, round(c,6)+0.0 AS c FROM k"


# summaries
@query("summary_lineitem_d2", f"WITH {Z}, {FLAGS} {FLAT_SQL}")
def _(spark, d):
    return flat2(flags(spark, d))


@query("summary_suppliers_d2", f"WITH {Z}, {SUPPLIERS} {FLAT_SQL}")
def _(spark, d):
    return flat2(suppliers(spark, d))


@query("summary_part_brand", f"WITH {BRANDS} {FLAT_SQL}")
def _(spark, d):
    return flat2(brands(spark, d))


_D4 = ", ".join([f"avg(z{i}) AS m{i}" for i in range(1, 5)] + [f"covar_samp(z{i}, z{j}) AS c{i}{j}" for i in range(1, 5) for j in range(i, 5)])
_D4_OUT = ", ".join([f"round(m{i},6)+0.0 AS m{i}" for i in range(1, 5)] + [f"round(c{i}{j},6)+0.0 AS c{i}{j}" for i in range(1, 5) for j in range(i, 5)])


def flat4(df: DataFrame, *keys: str) -> DataFrame:
    slots = [(i, j) for i in range(1, 5) for j in range(i, 5)]
    return df.select(*keys, "n", *[r(F.element_at("mean", i)).alias(f"m{i}") for i in range(1, 5)], *[r(F.element_at("cov", k + 1)).alias(f"c{i}{j}") for k, (i, j) in enumerate(slots)])


@query("summary_lineitem_d4", f"WITH {Z}, k AS (SELECT ascii(l_returnflag)*1000+ascii(l_linestatus) AS id, count(*) AS n, {_D4} FROM z GROUP BY 1) SELECT CAST(id AS BIGINT) AS cluster_id, CAST(n AS BIGINT) AS n, {_D4_OUT} FROM k")
def _(spark, d):
    return flat4(flags(spark, d, 4), "cluster_id")


@query("summary_events_type", "SELECT CAST(ascii(event_type)*1000+length(event_type) AS BIGINT) AS cluster_id, CAST(count(*) AS BIGINT) AS n, round(avg(value),6)+0.0 AS m1, round(var_samp(value),4)+0.0 AS a FROM events WHERE value IS NOT NULL AND isfinite(value) GROUP BY 1")
def _(spark, d):
    return event_types(spark, d).select("cluster_id", "n", r(F.col("mean")[0]).alias("m1"), r(F.col("cov")[0], 4).alias("a"))


_EMB = "e AS (SELECT label, vec_id, unnest(range(1, 65)) AS i, unnest(embedding) AS x FROM embeddings)"


@query("summary_embeddings_label", f"WITH {_EMB} SELECT CAST(label AS BIGINT) AS cluster_id, CAST(i AS BIGINT) AS axis, CAST(count(*) AS BIGINT) AS n, round(avg(CAST(x AS DOUBLE)),6)+0.0 AS mean, round(var_samp(CAST(x AS DOUBLE)),6)+0.0 AS var FROM e GROUP BY 1, 2")
def _(spark, d):
    k = stats.with_diagonal(labels(spark, d, 64))
    return k.select("cluster_id", "n", F.posexplode(F.arrays_zip("mean", "diag")).alias("p", "x")).select("cluster_id", (F.col("p") + 1).cast("long").alias("axis"), "n", r("x.mean").alias("mean"), r("x.diag").alias("var"))


_EMB8 = "e AS (SELECT label, vec_id, i, CAST(embedding[i] AS DOUBLE) AS x FROM embeddings, range(1, 9) t(i))"


@query("summary_embeddings_d8", f"WITH {_EMB8} SELECT CAST(p.label AS BIGINT) AS cluster_id, CAST(p.i AS INTEGER) AS i, CAST(q.i AS INTEGER) AS j, CAST(count(*) AS BIGINT) AS n, round(covar_samp(p.x, q.x),7)+0.0 AS cov FROM e p JOIN e q ON p.vec_id = q.vec_id AND p.i <= q.i GROUP BY 1, 2, 3")
def _(spark, d):
    k = S.summarize_vectors_sql(tables.read_table(spark, d, "embeddings", ["label", "embedding"]), F.col("label"), "embedding", 8)
    ij = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(8)), lambda i: F.transform(F.sequence(i, F.lit(8)), lambda j: F.struct(i.alias("i"), j.alias("j")))))
    return k.select("cluster_id", "n", F.explode(F.arrays_zip("cov", ij.alias("ij"))).alias("x")).select("cluster_id", F.col("x.ij.i").alias("i"), F.col("x.ij.j").alias("j"), "n", r("x.cov", 7).alias("cov"))


@query("summary_conversations_role", "SELECT role, CAST(count(*) AS BIGINT) AS n, round(avg(CAST(length(text) AS DOUBLE)),6)+0.0 AS m1, round(avg(CAST(turn AS DOUBLE)),6)+0.0 AS m2, round(covar_samp(CAST(length(text) AS DOUBLE), CAST(turn AS DOUBLE)),4)+0.0 AS b FROM conversations WHERE text IS NOT NULL AND turn IS NOT NULL GROUP BY role")
def _(spark, d):
    c = tables.read_table(spark, d, "conversations", ["role", "turn", "text"]).filter("text is not null and turn is not null").select("role", F.char_length("text").cast("double").alias("x"), F.col("turn").cast("double").alias("y"))
    return c.groupBy("role").agg(F.count(F.lit(1)).alias("n"), r(F.avg("x")).alias("m1"), r(F.avg("y")).alias("m2"), r(F.covar_samp("x", "y"), 4).alias("b"))


@query("summary_labels_quality", "SELECT CAST(quality AS BIGINT) AS cluster_id, CAST(count(*) AS BIGINT) AS n, round(avg(CAST(n_chars AS DOUBLE)),4)+0.0 AS m1 FROM labels JOIN documents USING (doc_id) WHERE quality IS NOT NULL AND n_chars IS NOT NULL GROUP BY 1")
def _(spark, d):
    both = tables.read_table(spark, d, "documents", ["doc_id", "n_chars"]).join(tables.read_table(spark, d, "labels", ["doc_id", "quality"]), "doc_id").filter("quality is not null")
    return S.summarize_columns(both, F.col("quality"), ["n_chars"]).select("cluster_id", "n", r(F.col("mean")[0], 4).alias("m1"))


@query("standardize_lineitem", f"WITH {Z} SELECT CAST(count(*) AS BIGINT) AS n, round(min(z1),6)+0.0 AS lo1, round(max(z1),6)+0.0 AS hi1, round(min(z2),6)+0.0 AS lo2, round(max(z2),6)+0.0 AS hi2, round(avg(z1*z2),6)+0.0 AS cross12 FROM z")
def _(spark, d):
    return scenarios.lineitem_z(spark, d).agg(F.count(F.lit(1)).alias("n"), r(F.min("z1")).alias("lo1"), r(F.max("z1")).alias("hi1"), r(F.min("z2")).alias("lo2"), r(F.max("z2")).alias("hi2"), r(F.avg(F.col("z1") * F.col("z2"))).alias("cross12"))


@query("scan_lineitem_features", "SELECT l_quantity, l_extendedprice, l_discount, l_tax FROM lineitem WHERE l_quantity >= 49")
def _(spark, d):
    return tables.read_table(spark, d, "lineitem", ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]).filter("l_quantity >= 49")


@query("doc_hash_features", "WITH w AS (SELECT doc_id, unnest(string_split_regex(lower(text), '[ \\t\\n\\x0B\\f\\r]+')) AS t FROM documents), c AS (SELECT doc_id, CAST(('0x' || substr(md5(t),1,8)) AS BIGINT) % 100 AS bucket FROM w WHERE t <> '') SELECT doc_id, CAST(bucket AS INTEGER) AS bucket, round(sqrt(count(*) * 1.0 / sum(count(*)) OVER (PARTITION BY doc_id)),6) AS x FROM c GROUP BY doc_id, bucket")
def _(spark, d):
    docs = tables.read_table(spark, d, "documents", ["doc_id", "lang", "text"])
    return tables.hashed_words(docs).select("doc_id", F.posexplode("vec").alias("bucket", "x")).filter("x > 0").select("doc_id", "bucket", r("x").alias("x"))


@query("events_features", "SELECT event_id, date_trunc('day', ts) AS day, CAST(hour(ts) AS DOUBLE) AS hour, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS k FROM events")
def _(spark, d):
    return tables.events(spark, d).select("event_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"), "hour", "k")


@query("events_clean_counts", "SELECT event_type, CAST(count(*) FILTER (WHERE value IS NOT NULL AND isfinite(value)) AS BIGINT) AS n_used, CAST(count(*) FILTER (WHERE value IS NULL OR NOT isfinite(value)) AS BIGINT) AS n_rejected FROM events GROUP BY event_type")
def _(spark, d):
    return S.clean_counts(tables.read_table(spark, d, "events", ["event_type", "value"]), ["event_type"], ["value"])


@query("cluster_distinct_suppliers", "SELECT l_returnflag, l_linestatus, CAST(count(DISTINCT l_suppkey) AS BIGINT) AS n_distinct FROM lineitem GROUP BY ALL")
def _(spark, d):
    return S.distinct_per_cluster(tables.read_table(spark, d, "lineitem", ["l_returnflag", "l_linestatus", "l_suppkey"]), ["l_returnflag", "l_linestatus"], "l_suppkey")


@query("sampled_summary", f"WITH {Z}, k AS (SELECT ascii(l_returnflag)*1000+ascii(l_linestatus) AS id, count(*) AS n, avg(z1) AS m1, avg(z2) AS m2, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c FROM z WHERE l_orderkey % 10 = 0 GROUP BY 1) {FLAT_SQL}")
def _(spark, d):
    # the feature is the sample: how a summary of every tenth order compares with the whole
    li = scenarios.lineitem_z(spark, d, 2, ("l_orderkey", "l_returnflag", "l_linestatus")).filter("l_orderkey % 10 = 0")
    return flat2(S.summarize_columns(li, flag_id(), ["z1", "z2"]))


_SETS = "SELECT {flag} AS flag, {status} AS status, CAST(count(*) AS BIGINT) AS n, round(avg(z1),6)+0.0 AS m1, round(var_samp(z1),6)+0.0 AS a, round(covar_samp(z1,z2),6)+0.0 AS b FROM z GROUP BY {by}"
for _name, _by, _spark_by in (("rollup_summary", "ROLLUP(l_returnflag, l_linestatus)", "rollup"), ("cube_summary", "CUBE(l_returnflag, l_linestatus)", "cube")):

    @query(_name, f"WITH {Z} " + _SETS.format(flag="l_returnflag", status="l_linestatus", by=_by))
    def _(spark, d, kind=_spark_by):
        li = scenarios.lineitem_z(spark, d, 2, ("l_returnflag", "l_linestatus"))
        return getattr(li, kind)("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), r(F.avg("z1")).alias("m1"), r(F.var_samp("z1")).alias("a"), r(F.covar_samp("z1", "z2")).alias("b")).withColumnsRenamed({"l_returnflag": "flag", "l_linestatus": "status"})


@query("grouping_sets_summary", f"WITH {Z} " + _SETS.format(flag="l_returnflag", status="l_linestatus", by="GROUPING SETS ((l_returnflag), (l_linestatus))"))
def _(spark, d):
    li = scenarios.lineitem_z(spark, d, 2, ("l_returnflag", "l_linestatus"))
    flag, status = F.col("l_returnflag"), F.col("l_linestatus")
    return li.groupingSets([[flag], [status]], flag, status).agg(F.count(F.lit(1)).alias("n"), r(F.avg("z1")).alias("m1"), r(F.var_samp("z1")).alias("a"), r(F.covar_samp("z1", "z2")).alias("b")).withColumnsRenamed({"l_returnflag": "flag", "l_linestatus": "status"})


@query("rollup_equals_fusion", f"WITH {Z}, k AS (SELECT ascii(l_returnflag) AS id, count(*) AS n, avg(z1) AS m1, avg(z2) AS m2, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c FROM z GROUP BY 1) {FLAT_SQL}")
def _(spark, d):
    # the upper level of a rollup is the fusion of the clusters of the lower one: rows are not read again
    low = flags(spark, d).withColumn("upper", F.floor(F.col("cluster_id") / 1000))
    return flat2(fuse.fuse_by(low, ["upper"]).withColumn("cluster_id", F.col("upper")))


# derived statistics
@query("cluster_lndet_d2", f"WITH {Z}, {SUPPLIERS} SELECT CAST(id AS BIGINT) AS cluster_id, round(ln(a*c-b*b),6)+0.0 AS lndet FROM k")
def _(spark, d):
    return stats.flat2(suppliers(spark, d)).select("cluster_id", r("lndet").alias("lndet"))


@query("cluster_hadamard_d64", f"WITH {_EMB}, v AS (SELECT label, i, var_samp(CAST(x AS DOUBLE)) AS var FROM e GROUP BY 1, 2) SELECT CAST(label AS BIGINT) AS cluster_id, round(sum(ln(var)),6)+0.0 AS ln_hadamard, round(sum(var),6)+0.0 AS trace FROM v GROUP BY 1")
def _(spark, d):
    return stats.with_diagonal(labels(spark, d, 64)).select("cluster_id", r("ln_hadamard").alias("ln_hadamard"), r("trace").alias("trace"))


@query("cluster_trace", f"WITH {Z}, {FLAGS} SELECT CAST(id AS BIGINT) AS cluster_id, round(a+c,6)+0.0 AS trace FROM k")
def _(spark, d):
    return stats.with_diagonal(flags(spark, d)).select("cluster_id", r("trace").alias("trace"))


@query("hadamard_gap_d2", f"WITH {Z}, {SUPPLIERS} SELECT CAST(id AS BIGINT) AS cluster_id, round(ln(a*c/(a*c-b*b)),6)+0.0 AS gap FROM k")
def _(spark, d):
    return stats.flat2(suppliers(spark, d)).select("cluster_id", r(F.col("ln_hadamard") - F.col("lndet")).alias("gap"))


@query("volume_d2", f"WITH {Z}, {SUPPLIERS} SELECT CAST(id AS BIGINT) AS cluster_id, round(a*c-b*b,6)+0.0 AS volume, (a*c-b*b) < 2.2250738585072014e-308 AS underflow FROM k")
def _(spark, d):
    return stats.flat2(suppliers(spark, d)).select("cluster_id", r("volume").alias("volume"), (F.col("volume") < 2.2250738585072014e-308).alias("underflow"))


@query("ellipse_2sigma", f"WITH {Z}, {SUPPLIERS}, h AS (SELECT *, (a+c)/2 AS h, sqrt(((a-c)/2)*((a-c)/2)+b*b) AS g FROM k) SELECT CAST(id AS BIGINT) AS cluster_id, round(m1,6)+0.0 AS cx, round(m2,6)+0.0 AS cy, round(2*sqrt(h+g),6)+0.0 AS semi_major, round(2*sqrt(greatest(h-g,0)),6)+0.0 AS semi_minor, round(0.5*atan2(2*b,a-c),6)+0.0 AS angle FROM h")
def _(spark, d):
    return rounded(stats.ellipse(suppliers(spark, d)), "cx", "cy", "semi_major", "semi_minor", "angle")


@query("cluster_stats_d64")
def _(spark, d):
    return stats.with_stats(labels(spark, d, 64)).select("cluster_id", "n", "lndet", "ln_hadamard", "trace", "lam_max", "rank", "status")


@query("cluster_stats_docs100")
def _(spark, d):
    vec = tables.hashed_words(tables.read_table(spark, d, "documents", ["doc_id", "lang", "text"]))
    lang = F.ascii("lang") * 1000 + F.ascii(F.substring("lang", 2, 1))
    return stats.with_stats(S.summarize_vectors(vec, lang, "vec", 100)).select("cluster_id", "n", "lndet", F.exp("lndet").alias("volume"), "ln_hadamard", "rank", "status")


@query("assign_lineitem", f"WITH {Z}, {FLAGS}, rz AS (SELECT row_number() OVER () AS rid, z1, z2 FROM z), s AS (SELECT id, row_number() OVER (PARTITION BY rid ORDER BY (c*(z1-m1)*(z1-m1)-2*b*(z1-m1)*(z2-m2)+a*(z2-m2)*(z2-m2))/(a*c-b*b)+ln(a*c-b*b), id) AS r FROM rz, k) SELECT CAST(id AS BIGINT) AS cluster_id, CAST(count(*) AS BIGINT) AS n FROM s WHERE r = 1 GROUP BY 1")
def _(spark, d):
    li = scenarios.lineitem_z(spark, d)
    return stats.assign2(li, "z1", "z2", stored(flags(spark, d))).groupBy(F.col("assigned").alias("cluster_id")).agg(F.count(F.lit(1)).alias("n"))


@query("assign_lineitem_any_d", SQL["assign_lineitem"])
def _(spark, d):
    return stats.assign(scenarios.lineitem_z(spark, d).select("z1", "z2"), ["z1", "z2"], stored(flags(spark, d)), 2, blocks=2).groupBy(F.col("assigned").alias("cluster_id")).agg(F.count(F.lit(1)).alias("n"))


@query("assign_events", "WITH k AS (SELECT CAST(ascii(event_type)*1000+length(event_type) AS BIGINT) AS id, avg(value) AS m, var_samp(value) AS s FROM events WHERE value IS NOT NULL AND isfinite(value) GROUP BY 1), a AS (SELECT event_id, id, row_number() OVER (PARTITION BY event_id ORDER BY (value-m)*(value-m)/s+ln(s), id) AS r FROM events, k WHERE value IS NOT NULL AND isfinite(value)) SELECT event_id, id AS assigned FROM a WHERE r = 1")
def _(spark, d):
    ev = tables.read_table(spark, d, "events", ["event_id", "value"]).filter(S.usable(["value"]))
    return summaries.assigned_events(ev, stored(event_types(spark, d))).select("event_id", "assigned")


@query("sampling_error_o", f"WITH {Z}, {FLAGS}, {PAIRS}, {FLAGS.replace('k AS', 'k2 AS').replace('FROM z', 'FROM z WHERE l_orderkey % 10 = 0')}, {second(PAIRS)} SELECT y.left_id, y.right_id, round({MEASURE_SQL['o']},6)+0.0 AS o, round((SELECT {MEASURE_SQL['o']} FROM y2 WHERE y2.left_id = y.left_id AND y2.right_id = y.right_id),6)+0.0 AS o_sample FROM y")
def _(spark, d):
    li = scenarios.lineitem_z(spark, d, 2, ("l_orderkey", "l_returnflag", "l_linestatus"))
    of = lambda rows: measures.measure_pairs(pairs.all_pairs(stored(S.summarize_columns(rows, flag_id(), ["z1", "z2"])), ["n", "mean", "cov"]), 2, ["o"])
    # the feature is the sample: how far the overlap of every tenth order lies from that of all
    sample = of(li.filter("l_orderkey % 10 = 0")).select("left_id", "right_id", r("o").alias("o_sample"))
    return of(li).select("left_id", "right_id", r("o").alias("o")).join(sample, ["left_id", "right_id"])


# measures
def d2_pairs(spark, d, of=flags):
    return measures.flat_pairs2(pairs.all_pairs(stored(of(spark, d)), ["n", "mean", "cov"]))


def one_measure(name, literal=False, k=6):
    def run(spark, d):
        return d2_pairs(spark, d).select("left_id", "right_id", r(measures.measure2(name, literal), k).alias(name))

    return run


for _m in ("b", "js", "w", "vr", "ab", "o", "oh"):
    query(f"measure_{_m}_d2", f"WITH {Z}, {FLAGS}, {PAIRS} SELECT left_id, right_id, round({MEASURE_SQL[_m]},6)+0.0 AS {_m} FROM y")(one_measure(_m, _m == "js"))


@query("measure_kl_d2", f"WITH {Z}, {FLAGS}, {PAIRS} SELECT left_id, right_id, round({MEASURE_SQL['kl1']},6)+0.0 AS kl_left, round({MEASURE_SQL['kl2']},6)+0.0 AS kl_right FROM y")
def _(spark, d):
    return d2_pairs(spark, d).select("left_id", "right_id", r(measures.measure2("kl_left")).alias("kl_left"), r(measures.measure2("kl_right")).alias("kl_right"))


_ALL = ", ".join(f"round({MEASURE_SQL[m]},6)+0.0 AS {m}" for m in measures.MEASURES)


@query("measures_all_d2", f"WITH {Z}, {SUPPLIERS}, {PAIRS} SELECT left_id, right_id, {_ALL} FROM y")
def _(spark, d):
    # F.round goes through decimals, which takes longer than the measures
    at6 = lambda m: (F.rint(F.col(m) * 1e6) / 1e6 + 0.0).alias(m)
    return tiles.measured(stored(suppliers(spark, d))).select("left_id", "right_id", *[at6(m) for m in measures.MEASURES])


@query("sql_o_d2", f"WITH {Z}, {FLAGS}, {PAIRS} SELECT left_id, right_id, round({MEASURE_SQL['o']},6)+0.0 AS o FROM y")
def _(spark, d):
    stored(flat2_raw(flags(spark, d))).createOrReplaceTempView("clusters")
    return spark.sql(f"WITH k AS (SELECT * FROM clusters), {PAIRS} SELECT left_id, right_id, round({MEASURE_SQL['o']},6)+0.0D AS o FROM y")


def flat2_raw(df: DataFrame) -> DataFrame:
    at = F.element_at
    return df.select(F.col("cluster_id").alias("id"), "n", at("mean", 1).alias("m1"), at("mean", 2).alias("m2"), at("cov", 1).alias("a"), at("cov", 2).alias("b"), at("cov", 3).alias("c"))


@query("js_equals_b", f"WITH {Z}, {SUPPLIERS}, {PAIRS} SELECT CAST(count(*) AS BIGINT) AS n_pairs, max(abs(({MEASURE_SQL['kl1']}+{MEASURE_SQL['kl2']})/2-({MEASURE_SQL['b']}))) < 1e-9 AS equal FROM y")
def _(spark, d):
    x = tiles.largest_gap(stored(suppliers(spark, d)), ["js_literal", "b"], lambda v: abs(v["js_literal"] - v["b"]))
    return x.select("n_pairs", (F.col("gap") < 1e-9).alias("equal"))


@query("o_equals_ln2vr", f"WITH {Z}, {SUPPLIERS}, {PAIRS} SELECT CAST(count(*) AS BIGINT) AS n_pairs, max(abs({MEASURE_SQL['o']}-ln(2*({MEASURE_SQL['vr']})))) < 1e-9 AS equal FROM y")
def _(spark, d):
    x = tiles.largest_gap(stored(suppliers(spark, d)), ["o", "vr"], lambda v: abs(v["o"] - np.log(2 * v["vr"])))
    return x.select("n_pairs", (F.col("gap") < 1e-9).alias("equal"))


@query("o_parts_d2", f"WITH {Z}, {FLAGS}, {PAIRS} SELECT left_id, right_id, round(ln(dw/((e1+e2)/2)),6)+0.0 AS o_spread, round(ln(df/dw),6)+0.0 AS o_gap, round({MEASURE_SQL['o']},6)+0.0 AS o FROM y")
def _(spark, d):
    return d2_pairs(spark, d).select("left_id", "right_id", *[r(measures.measure2(m)).alias(m) for m in ("o_spread", "o_gap", "o")])


@query("literal_forms_d2", f"WITH {Z}, {FLAGS}, {PAIRS} SELECT left_id, right_id, round({MEASURE_SQL['b']},6)+0.0 AS b_literal, round({MEASURE_SQL['o']},6)+0.0 AS o_literal FROM y")
def _(spark, d):
    return rounded(measures.literal_measures(pairs.all_pairs(stored(flags(spark, d)), ["n", "mean", "cov"]), 2), "b_literal", "o_literal").drop("model_id")


@query("literal_forms_docs100")
def _(spark, d):
    vec = tables.hashed_words(tables.read_table(spark, d, "documents", ["doc_id", "lang", "text"]))
    k = stored(S.summarize_vectors(vec, F.ascii("lang") * 1000 + F.ascii(F.substring("lang", 2, 1)), "vec", 100))
    return measures.literal_measures(pairs.all_pairs(k, ["n", "mean", "cov"]), 100).join(measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), 100, ["b", "o"]).drop("n1", "n2", "model_id"), ["left_id", "right_id"]).drop("model_id")


@query("measure_o_udf", SQL["measure_o_d2"])
def _(spark, d):
    sqlfuncs.register(spark)
    pairs.all_pairs(stored(flags(spark, d)), ["n", "mean", "cov"]).createOrReplaceTempView("cluster_pairs")
    return spark.sql("SELECT left_id, right_id, round(gauss_o(p, q), 6) + 0.0D AS o FROM cluster_pairs")


_E1 = "k AS (SELECT CAST(ascii(event_type)*1000+length(event_type) AS BIGINT) AS id, count(*) AS n, avg(value) AS m, var_samp(value) AS s FROM events WHERE value IS NOT NULL AND isfinite(value) GROUP BY 1), p AS (SELECT x.id AS left_id, y.id AS right_id, x.n AS n1, y.n AS n2, x.m-y.m AS d, x.s AS s1, y.s AS s2 FROM k x JOIN k y ON x.id < y.id)"


@query("measure_o_d1", f"WITH {_E1} SELECT left_id, right_id, round(ln(2*(((n1-1)*s1+(n2-1)*s2+n1*n2/(n1+n2)*d*d)/(n1+n2-1))/(s1+s2)),6)+0.0 AS o FROM p")
def _(spark, d):
    return measures.measures1(pairs.all_pairs(stored(event_types(spark, d)), ["n", "mean", "cov"]), ["o"]).select("left_id", "right_id", r("o").alias("o"))


@query("measure_w_d1", f"WITH {_E1} SELECT left_id, right_id, round(d*d+(sqrt(s1)-sqrt(s2))*(sqrt(s1)-sqrt(s2)),5)+0.0 AS w FROM p")
def _(spark, d):
    return measures.measures1(pairs.all_pairs(stored(event_types(spark, d)), ["n", "mean", "cov"]), ["w"]).select("left_id", "right_id", r("w", 5).alias("w"))


def _oh_sql(rows: str, axes: str) -> str:
    return f"WITH {rows}, k AS ({axes}), f AS (SELECT p.id AS left_id, q.id AS right_id, sum(ln(((p.n-1)*p.v+(q.n-1)*q.v+p.n*q.n/(p.n+q.n)*(p.m-q.m)*(p.m-q.m))/(p.n+q.n-1))) AS hf, sum(ln(p.v)) AS h1, sum(ln(q.v)) AS h2 FROM k p JOIN k q ON p.i = q.i AND p.id < q.id GROUP BY 1, 2) SELECT left_id, right_id, round(ln(2.0)+hf-(greatest(h1,h2)+ln(1+exp(-abs(h1-h2)))),6)+0.0 AS oh FROM f"


def emb_axes(dim: int) -> str:
    return f"e AS (SELECT label AS id, vec_id AS rid, i, CAST(embedding[i] AS DOUBLE) AS x FROM embeddings, range(1, {dim + 1}) t(i))"


def oh_pairs(k: DataFrame) -> DataFrame:
    x = stored(stats.with_diagonal(k).select("model_id", "cluster_id", "n", "mean", "diag", "ln_hadamard"))
    return measures.overlap_oh(pairs.all_pairs(x, ["n", "mean", "diag", "ln_hadamard"])).select("left_id", "right_id", r("oh").alias("oh"))


@query("measure_oh_d4", _oh_sql(f"{Z}, u AS (SELECT ascii(l_returnflag)*1000+ascii(l_linestatus) AS id, i, [z1,z2,z3,z4][i] AS x FROM z, range(1,5) t(i))", "SELECT CAST(id AS BIGINT) AS id, i, count(*) AS n, avg(x) AS m, var_samp(x) AS v FROM u GROUP BY 1, 2"))
def _(spark, d):
    return oh_pairs(flags(spark, d, 4))


@query("measure_oh_d64", _oh_sql(_EMB, "SELECT CAST(label AS BIGINT) AS id, i, count(*) AS n, avg(CAST(x AS DOUBLE)) AS m, var_samp(CAST(x AS DOUBLE)) AS v FROM e GROUP BY 1, 2"))
def _(spark, d):
    return oh_pairs(labels(spark, d, 64))


# ln of a variance of zero is an error in this engine, and minus infinity in the other
_DOCS100 = (
    "w AS (SELECT doc_id, lang, unnest(string_split_regex(lower(text), '[ \\t\\n\\x0B\\f\\r]+')) AS t FROM documents), c AS (SELECT doc_id, lang, CAST(('0x' || substr(md5(t),1,8)) AS BIGINT) % 100 AS bucket, count(*) AS k FROM w WHERE t <> '' GROUP BY ALL), "
    "td AS (SELECT doc_id, lang, sum(k) AS total FROM c GROUP BY ALL), e AS (SELECT ascii(td.lang)*1000+ascii(substr(td.lang,2,1)) AS id, td.doc_id AS rid, i, sqrt(coalesce(k,0)*1.0/total) AS x FROM td CROSS JOIN range(100) b(i) LEFT JOIN c ON c.doc_id = td.doc_id AND c.bucket = i)"
)


@query("measure_oh_d100", _oh_sql(_DOCS100, "SELECT CAST(id AS BIGINT) AS id, i, count(*) AS n, avg(x) AS m, var_samp(x) AS v FROM e GROUP BY 1, 2"))
def _(spark, d):
    vec = tables.hashed_words(tables.read_table(spark, d, "documents", ["doc_id", "lang", "text"]))
    return oh_pairs(S.summarize_vectors(vec, F.ascii("lang") * 1000 + F.ascii(F.substring("lang", 2, 1)), "vec", 100))


@query("embeddings_o_d2", "WITH k AS (SELECT CAST(label AS BIGINT) AS id, count(*) AS n, avg(x) AS m1, avg(y) AS m2, var_samp(x) AS a, covar_samp(x,y) AS b, var_samp(y) AS c FROM (SELECT label, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings) GROUP BY 1), " + PAIRS + f" SELECT left_id, right_id, round({MEASURE_SQL['o']},6)+0.0 AS o FROM y")
def _(spark, d):
    return measures.measure_pairs(pairs.all_pairs(stored(labels(spark, d, 2)), ["n", "mean", "cov"]), 2, ["o"]).select("left_id", "right_id", r("o").alias("o"))


for _dim in (4, 8, 16, 64):

    # the SQL iterates matrix products for w, which takes minutes at 64 axes
    @query(f"measures_embeddings_d{_dim}", all_measures(emb_axes(_dim), _dim) if _dim < 64 else None)
    def _(spark, d, dim=_dim):
        # 64 axes and fewer samples at small scale: a ridge keeps singular clusters measurable
        return rounded(measures.measure_pairs(pairs.all_pairs(stored(labels(spark, d, dim)), ["n", "mean", "cov"]), dim, engine="arrow", ridge=1e-3 if dim == 64 else None).drop("model_id"), *measures.MEASURES)


@query("measures_lineitem_d4", all_measures(f"{Z}, e AS (SELECT ascii(l_returnflag)*1000+ascii(l_linestatus) AS id, rid, i, [z1,z2,z3,z4][i] AS x FROM (SELECT *, row_number() OVER () AS rid FROM z), range(1,5) t(i))", 4))
def _(spark, d):
    return rounded(measures.measure_pairs(pairs.all_pairs(stored(flags(spark, d, 4)), ["n", "mean", "cov"]), 4).drop("model_id"), *measures.MEASURES)


@query("measures_docs_d100")
def _(spark, d):
    vec = tables.hashed_words(tables.read_table(spark, d, "documents", ["doc_id", "lang", "text"]))
    k = stored(S.summarize_vectors(vec, F.ascii("lang") * 1000 + F.ascii(F.substring("lang", 2, 1)), "vec", 100))
    return measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), 100)


def _null_sql(dim: int) -> str:
    """Expected o of two samples of one Gaussian, over y: a sum over the axes of what a Wishart matrix's log-determinant loses."""
    at = lambda nu: f"({nu}-i)/2.0"
    biased = lambda nu: f"sum({psi(at(nu))})+{dim}*ln(2.0/max({nu}))"
    return f"{biased('(n1+n2-1)')}-0.5*({biased('(n1-1)')}+{biased('(n2-1)')})-sum({psi1(at('(n1-1)'))}+{psi1(at('(n2-1)'))})/8"


@query("null_corrected_o", f"WITH RECURSIVE {matrix_pairs(emb_axes(8), 8)}, nu AS (SELECT left_id, right_id, {_null_sql(8)} AS o_null FROM y, range(8) t(i) GROUP BY 1, 2) SELECT CAST(left_id AS BIGINT) AS left_id, CAST(right_id AS BIGINT) AS right_id, CAST(n1 AS BIGINT) AS n1, CAST(n2 AS BIGINT) AS n2, round(o,6)+0.0 AS o, round(o_null,6)+0.0 AS o_null, round(o-o_null,6)+0.0 AS o_corrected FROM y JOIN nu USING (left_id, right_id)")
def _(spark, d):
    x = measures.null_corrected(measures.measure_pairs(pairs.all_pairs(stored(labels(spark, d, 8)), ["n", "mean", "cov"]), 8, ["o"]), 8)
    return x.select("left_id", "right_id", "n1", "n2", *[r(c).alias(c) for c in ("o", "o_null", "o_corrected")])


_LONG = " UNION ALL ".join(f"SELECT left_id, right_id, '{m}' AS measure, round({MEASURE_SQL[m]},6)+0.0 AS value FROM y" for m in measures.MEASURES)


@query("pairs_long", f"WITH {Z}, {FLAGS}, {PAIRS} {_LONG}")
def _(spark, d):
    wide = measures.measure_pairs(pairs.all_pairs(stored(flags(spark, d)), ["n", "mean", "cov"]), 2)
    return wide.unpivot(["left_id", "right_id"], measures.MEASURES, "measure", "value").select("left_id", "right_id", "measure", r("value").alias("value"))


@query("measure_map", f"WITH {Z}, {FLAGS}, {PAIRS}, l AS ({_LONG}) SELECT * FROM l WHERE value > 0")
def _(spark, d):
    wide = measures.measure_pairs(pairs.all_pairs(stored(flags(spark, d)), ["n", "mean", "cov"]), 2)
    m = F.map_from_arrays(F.array(*[F.lit(x) for x in measures.MEASURES]), F.array(*[r(x) for x in measures.MEASURES]))
    return wide.select("left_id", "right_id", F.explode(F.map_filter(m, lambda _, v: v > 0)).alias("measure", "value"))


# candidates and graph
def o_pairs(spark, d, of=disc_clusters):
    return measures.measure_pairs(pairs.all_pairs(stored(of(spark, d)), ["n", "mean", "cov"]), 2)


_O = f"o AS (SELECT left_id, right_id, {MEASURE_SQL['o']} AS o, {MEASURE_SQL['oh']} AS oh, {MEASURE_SQL['b']} AS b FROM y)"
_DISC_O = f"{Z}, {DISCS}, {PAIRS}, {_O}"
_EDGE = "e AS (SELECT left_id, right_id, o AS weight FROM o WHERE o < 1.5), g AS (SELECT left_id AS x, right_id AS y FROM e UNION SELECT right_id, left_id FROM e)"


@query("pairs_all", f"WITH {Z}, {SUPPLIERS} SELECT CAST(p.id AS BIGINT) AS left_id, CAST(q.id AS BIGINT) AS right_id FROM k p JOIN k q ON p.id < q.id")
def _(spark, d):
    return pairs.all_pairs(stored(suppliers(spark, d)), ["n"]).select("left_id", "right_id")


@query("pairs_all_blocks", f"WITH {Z}, {SUPPLIERS} SELECT CAST(p.id AS BIGINT) AS left_id, CAST(q.id AS BIGINT) AS right_id FROM k p JOIN k q ON p.id < q.id")
def _(spark, d):
    return pairs.all_pairs(stored(suppliers(spark, d)), ["n"], blocks=4).select("left_id", "right_id")


@query("candidates_box_d2", f"WITH {Z}, {DISCS} SELECT CAST(p.id AS BIGINT) AS left_id, CAST(q.id AS BIGINT) AS right_id FROM k p JOIN k q ON p.id < q.id WHERE p.m1-2*sqrt(p.a) <= q.m1+2*sqrt(q.a) AND q.m1-2*sqrt(q.a) <= p.m1+2*sqrt(p.a) AND p.m2-2*sqrt(p.c) <= q.m2+2*sqrt(q.c) AND q.m2-2*sqrt(q.c) <= p.m2+2*sqrt(p.c)")
def _(spark, d):
    return pairs.box_candidates(stored(disc_clusters(spark, d))).select("left_id", "right_id")


@query("candidates_bound_d2", f"WITH {Z}, {DISCS}, {PAIRS}, v AS (SELECT *, (n1-1)/(n1+n2-1) AS w1, (n2-1)/(n1+n2-1) AS w2, n1*n2/((n1+n2)*(n1+n2-1)) AS cc FROM y), bd AS (SELECT left_id, right_id, ln(2.0)+2*ln(w1*sqrt(e1)+w2*sqrt(e2))+ln(1+cc*(d1*d1+d2*d2)/(w1*(a1+c1)+w2*(a2+c2)))-ln(e1+e2) AS bound FROM v) SELECT left_id, right_id, round(bound,6)+0.0 AS bound FROM bd WHERE bound < 1.5")
def _(spark, d):
    k = stats.with_diagonal(disc_clusters(spark, d)).withColumn("lndet", stats.lndet2(F.col("n"), F.col("cov")[0], F.col("cov")[1], F.col("cov")[2]))
    x = pairs.lower_bound(pairs.all_pairs(stored(k), ["n", "mean", "lndet", "trace"]), 2)
    return x.filter("bound < 1.5").select("left_id", "right_id", r("bound").alias("bound"))


@query("candidates_oh_d64", "SELECT * FROM (" + SQL["measure_oh_d64"] + ") WHERE oh < 0.6")
def _(spark, d):
    return oh_pairs(labels(spark, d, 64)).filter("oh < 0.6")


@query("candidate_recall", f"WITH {_DISC_O} SELECT CAST(count(*) FILTER (WHERE o < 1.5) AS BIGINT) AS n_edges, CAST(count(*) FILTER (WHERE o < 1.5 AND oh < 1.5) AS BIGINT) AS n_found, CAST(count(*) FILTER (WHERE oh < 1.5) AS BIGINT) AS n_candidates FROM o")
def _(spark, d):
    return o_pairs(spark, d).agg(F.count_if(F.col("o") < 1.5).alias("n_edges"), F.count_if((F.col("o") < 1.5) & (F.col("oh") < 1.5)).alias("n_found"), F.count_if(F.col("oh") < 1.5).alias("n_candidates"))


_BOX = "p.m1-2*sqrt(p.a) <= q.m1+2*sqrt(q.a) AND q.m1-2*sqrt(q.a) <= p.m1+2*sqrt(p.a) AND p.m2-2*sqrt(p.c) <= q.m2+2*sqrt(q.c) AND q.m2-2*sqrt(q.c) <= p.m2+2*sqrt(p.c)"


@query("candidate_recall_box", f"WITH {_DISC_O}, bx AS (SELECT CAST(p.id AS BIGINT) AS left_id, CAST(q.id AS BIGINT) AS right_id FROM k p JOIN k q ON p.id < q.id WHERE {_BOX}) SELECT CAST((SELECT count(*) FROM o WHERE o < 1.5) AS BIGINT) AS n_edges, CAST((SELECT count(*) FROM o JOIN bx USING (left_id, right_id) WHERE o < 1.5) AS BIGINT) AS n_found, CAST((SELECT count(*) FROM bx) AS BIGINT) AS n_candidates")
def _(spark, d):
    k = stored(disc_clusters(spark, d))
    near = pairs.box_candidates(k).select("left_id", "right_id", F.lit(True).alias("near"))
    x = measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), 2, ["o"]).join(near, ["left_id", "right_id"], "left")
    near_ = F.coalesce("near", F.lit(False))
    return x.agg(F.count_if(F.col("o") < 1.5).alias("n_edges"), F.count_if((F.col("o") < 1.5) & near_).alias("n_found"), F.count_if(near_).alias("n_candidates"))


_BOUND = "bd AS (SELECT left_id, right_id, ln(2.0)+2*ln(w1*sqrt(e1)+w2*sqrt(e2))+ln(1+cc*(d1*d1+d2*d2)/(w1*(a1+c1)+w2*(a2+c2)))-ln(e1+e2) AS bound FROM (SELECT *, (n1-1)/(n1+n2-1) AS w1, (n2-1)/(n1+n2-1) AS w2, n1*n2/((n1+n2)*(n1+n2-1)) AS cc FROM y))"


@query("candidate_pair_counts", f"WITH {_DISC_O}, {_BOUND}, bx AS (SELECT count(*) AS n FROM k p JOIN k q ON p.id < q.id WHERE {_BOX}) SELECT CAST((SELECT count(*) FROM o) AS BIGINT) AS n_none, CAST((SELECT count(*) FROM bd WHERE bound < 1.5) AS BIGINT) AS n_bound, CAST((SELECT count(*) FROM o WHERE oh < 1.5) AS BIGINT) AS n_oh, CAST((SELECT n FROM bx) AS BIGINT) AS n_box")
def _(spark, d):
    k = stored(disc_clusters(spark, d))
    counts = [fuse.candidate_pairs(k, 2, criterion=c).agg(F.count(F.lit(1)).alias(f"n_{c}")) for c in ("none", "bound", "oh", "box")]
    out = counts[0]
    for c in counts[1:]:
        out = out.crossJoin(c)  # one row each
    return out


@query("overlap_sign", f"WITH {Z}, {FLAGS}, {PAIRS} SELECT left_id, right_id, {MEASURE_SQL['o']} < 0 AS smaller FROM y")
def _(spark, d):
    return d2_pairs(spark, d).select("left_id", "right_id", (measures.measure2("o") < 0).alias("smaller"))


@query("overlap_edges", f"WITH {_DISC_O}, {_EDGE} SELECT left_id, right_id, round(weight,6)+0.0 AS weight FROM e")
def _(spark, d):
    return rounded(graph.edges(o_pairs(spark, d)), "weight")


@query("adjacency_o", f"WITH {_DISC_O}, {_EDGE} SELECT x AS left_id, y AS right_id FROM g")
def _(spark, d):
    return graph.adjacency(graph.edges(o_pairs(spark, d))).select("left_id", "right_id")


@query("adjacency_matrix", f"WITH {_DISC_O}, {_EDGE} SELECT CAST(p.id AS BIGINT) AS cluster_id, string_agg(CASE WHEN (p.id, q.id) IN (SELECT (x, y) FROM g) THEN '1' ELSE '0' END, '' ORDER BY q.id) AS row FROM k p, k q GROUP BY 1")
def _(spark, d):
    k = stored(disc_clusters(spark, d))
    found = graph.edges(measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), 2, ["o"]))
    return graph.adjacency_matrix(found, k).select("cluster_id", F.concat_ws("", F.transform("row", lambda v: v.cast("string"))).alias("row"))


def disc_graph(spark, d):
    k = stored(disc_clusters(spark, d))
    return k, tables.store(graph.edges(measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), 2, ["o"])), "edges")


@query("graph_degree", f"WITH {_DISC_O}, {_EDGE} SELECT CAST(id AS BIGINT) AS cluster_id, CAST(count(y) AS BIGINT) AS degree FROM k LEFT JOIN g ON k.id = g.x GROUP BY 1")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return graph.degrees(found, k)


@query("graph_isolated", f"WITH {_DISC_O}, {_EDGE} SELECT CAST(id AS BIGINT) AS cluster_id FROM k WHERE id NOT IN (SELECT x FROM g)")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return graph.isolated(k, found).select("cluster_id")


@query("clusters_touched", f"WITH {_DISC_O}, {_EDGE} SELECT CAST(id AS BIGINT) AS cluster_id FROM k WHERE id IN (SELECT x FROM g)")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return graph.touched(k, found).select("cluster_id")


_COMP = "reach(x, y) AS (SELECT id, id FROM k UNION SELECT r.x, g.y FROM reach r JOIN g ON r.y = g.x), comp AS (SELECT x AS cluster_id, min(y) AS component_id FROM reach GROUP BY 1)"


@query("components", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_COMP} SELECT CAST(cluster_id AS BIGINT) AS cluster_id, CAST(component_id AS BIGINT) AS component_id FROM comp")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return graph.components(found, k)


@query("groups_components", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_COMP} SELECT CAST(component_id AS BIGINT) AS group_id, CAST(cluster_id AS BIGINT) AS cluster_id, CAST(count(*) OVER (PARTITION BY component_id) AS INTEGER) AS size FROM comp")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return cliques.disjoint_groups(found, k, "components").drop("exact")


_CLIQUES = "c(m) AS (SELECT [x, y] FROM g WHERE x < y UNION SELECT list_append(c.m, g.y) FROM c JOIN g ON g.x = c.m[len(c.m)] AND g.y > c.m[len(c.m)] WHERE (SELECT count(*) FROM g h WHERE h.y = g.y AND list_contains(c.m, h.x)) = len(c.m)), mx AS (SELECT m FROM c WHERE NOT EXISTS (SELECT 1 FROM k WHERE NOT list_contains(c.m, k.id) AND (SELECT count(*) FROM g h WHERE h.y = k.id AND list_contains(c.m, h.x)) = len(c.m)))"


@query("maximal_cliques", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_CLIQUES} SELECT array_to_string(m, ',') AS members, CAST(len(m) AS INTEGER) AS size FROM mx")
def _(spark, d):
    _, found = disc_graph(spark, d)
    return cliques.maximal_cliques(found).select(F.concat_ws(",", F.transform("members", lambda v: v.cast("string"))).alias("members"), "size")


@query("cliques_by_join", SQL["maximal_cliques"])
def _(spark, d):
    _, found = disc_graph(spark, d)
    return cliques.cliques_by_join(found).select(F.concat_ws(",", F.transform("members", lambda v: v.cast("string"))).alias("members"), "size")


@query("cliques_recursive", SQL["maximal_cliques"])
def _(spark, d):
    _, found = disc_graph(spark, d)
    return cliques.cliques_recursive(found).select(F.concat_ws(",", F.transform("members", lambda v: v.cast("string"))).alias("members"), "size")


# the largest clique of what is left, one after another: ties by least weight, then by smallest ids
_GROUPS = "w AS (SELECT m, len(m) AS k, (SELECT round(sum(weight), 12) FROM e WHERE list_contains(c.m, e.left_id) AND list_contains(c.m, e.right_id)) AS t FROM c), pick(step, m, taken) AS (SELECT 0, CAST([] AS BIGINT[]), CAST([] AS BIGINT[]) UNION ALL SELECT step + 1, m, list_concat(taken, m) FROM (SELECT p.step, p.taken, w.m, row_number() OVER (ORDER BY w.k DESC, w.t, w.m) AS r FROM pick p JOIN w ON NOT list_has_any(w.m, p.taken)) WHERE r = 1), gr AS (SELECT m[1] AS group_id, unnest(m) AS cluster_id, len(m) AS size FROM pick WHERE step > 0), grp AS (SELECT CAST(coalesce(gr.group_id, k.id) AS BIGINT) AS group_id, CAST(k.id AS BIGINT) AS cluster_id, CAST(coalesce(gr.size, 1) AS INTEGER) AS size FROM k LEFT JOIN gr ON gr.cluster_id = k.id)"


@query("disjoint_groups", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_CLIQUES}, {_GROUPS} SELECT group_id, cluster_id, size, true AS exact FROM grp")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return cliques.disjoint_groups(found, k)


@query("cliques_of_udtf", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_CLIQUES}, {_GROUPS} SELECT group_id, cluster_id FROM grp WHERE size > 1")
def _(spark, d):
    sqlfuncs.register(spark)
    _, found = disc_graph(spark, d)
    comp = graph.components(found).select(F.col("cluster_id").alias("left_id"), "component_id")
    found.join(comp, "left_id").createOrReplaceTempView("edges_by_component")
    return spark.sql("SELECT group_id, cluster_id FROM cliques_of(TABLE(edges_by_component) PARTITION BY component_id) WHERE group_id IN (SELECT group_id FROM cliques_of(TABLE(edges_by_component) PARTITION BY component_id) GROUP BY 1 HAVING count(*) > 1)")


@query("disjoint_groups_greedy")
def _(spark, d):
    k, found = disc_graph(spark, d)
    return cliques.disjoint_groups(found, k, "greedy")


@query("sql_surface", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_CLIQUES}, {_GROUPS} SELECT CAST((SELECT count(*) FROM k) AS BIGINT) AS n_clusters, CAST((SELECT count(*) FROM o) AS BIGINT) AS n_pairs, CAST((SELECT count(*) FROM e) AS BIGINT) AS n_edges, CAST((SELECT count(DISTINCT group_id) FROM grp) AS BIGINT) AS n_groups, CAST((SELECT sum(n) FROM k) AS BIGINT) AS n_rows")
def _(spark, d):
    surface.create_views(stored(disc_clusters(spark, d)), 2)
    return spark.sql("SELECT (SELECT count(*) FROM clusters) AS n_clusters, (SELECT count(*) FROM pairs) AS n_pairs, (SELECT count(*) FROM edges) AS n_edges, (SELECT count(DISTINCT group_id) FROM groups) AS n_groups, (SELECT sum(n) FROM fused) AS n_rows")


@query("groups_valid", f"WITH {Z}, {DISCS} SELECT CAST(count(*) AS BIGINT) AS n_clusters, true AS each_in_one_group, true AS all_pairs_are_edges FROM k")
def _(spark, d):
    k, found = disc_graph(spark, d)
    groups = tables.store(cliques.disjoint_groups(found, k), "groups")
    inside = groups.alias("p").join(groups.alias("q"), "group_id").filter("p.cluster_id < q.cluster_id").select(F.col("p.cluster_id").alias("left_id"), F.col("q.cluster_id").alias("right_id"))
    missing = inside.join(found, ["left_id", "right_id"], "left_anti").agg(F.count(F.lit(1)).alias("missing"))
    return groups.agg(F.count(F.lit(1)).alias("n_clusters"), (F.count_distinct("cluster_id") == F.count(F.lit(1))).alias("each_in_one_group")).crossJoin(missing).select("n_clusters", "each_in_one_group", (F.col("missing") == 0).alias("all_pairs_are_edges"))


@query("groups_with_singletons", f"WITH {_DISC_O}, {_EDGE}, best AS (SELECT x, min(y) AS y FROM g GROUP BY 1) SELECT CAST(id AS BIGINT) AS cluster_id, CAST(coalesce(least(id, y), id) AS BIGINT) AS group_id FROM k LEFT JOIN best ON id = x")
def _(spark, d):
    k, found = disc_graph(spark, d)
    best = graph.adjacency(found).groupBy(F.col("left_id").alias("cluster_id")).agg(F.min("right_id").alias("y"))
    return k.select("cluster_id").join(best, "cluster_id", "left").select("cluster_id", F.coalesce(F.least("cluster_id", "y"), F.col("cluster_id")).alias("group_id"))


for _name, _op, _sql in (
    ("edges_o_minus_b", "exceptAll", "SELECT left_id, right_id FROM o WHERE o < 1.5 EXCEPT ALL SELECT left_id, right_id FROM o WHERE b < 0.5"),
    ("edges_o_intersect_oh", "intersect", "SELECT left_id, right_id FROM o WHERE o < 1.5 INTERSECT SELECT left_id, right_id FROM o WHERE oh < 1.5"),
    ("edges_union", "union", "SELECT left_id, right_id FROM o WHERE o < 1.5 UNION SELECT left_id, right_id FROM o WHERE b < 0.5"),
    ("edges_union_all", "unionByName", "SELECT left_id, right_id FROM o WHERE o < 1.5 UNION ALL SELECT left_id, right_id FROM o WHERE b < 0.5"),
):

    @query(_name, f"WITH {_DISC_O} {_sql}")
    def _(spark, d, op=_op):
        m = tables.store(o_pairs(spark, d), "measured")
        one, two = m.filter("o < 1.5").select("left_id", "right_id"), m.filter("oh < 1.5" if op == "intersect" else "b < 0.5").select("left_id", "right_id")
        out = getattr(one, op)(two)
        return out.distinct() if op == "union" else out


@query("topk_overlap", f"WITH {Z}, {SUPPLIERS}, {PAIRS}, {_O} SELECT left_id, right_id, round(o,6)+0.0 AS o FROM o ORDER BY o, left_id, right_id LIMIT 10")
def _(spark, d):
    return tiles.least(stored(suppliers(spark, d)), "o", 10).select("left_id", "right_id", r("value").alias("o"))


_BOTH = "bo AS (SELECT left_id, right_id, o FROM o UNION ALL SELECT right_id, left_id, o FROM o)"


def both_ways(m: DataFrame) -> DataFrame:
    return m.select("left_id", "right_id", "o").unionByName(m.select(F.col("right_id").alias("left_id"), F.col("left_id").alias("right_id"), "o"))


@query("nearest_cluster_topk", f"WITH {Z}, {SUPPLIERS}, {PAIRS}, {_O}, {_BOTH} SELECT left_id, right_id, CAST(r AS INTEGER) AS place FROM (SELECT *, row_number() OVER (PARTITION BY left_id ORDER BY o, right_id) AS r FROM bo) WHERE r <= 3")
def _(spark, d):
    return tiles.nearest(stored(suppliers(spark, d)), "o", 3).select("left_id", "right_id", "place")


@query("overlap_rank", f"WITH {_DISC_O}, {_BOTH} SELECT left_id, right_id, CAST(rank() OVER w AS INTEGER) AS rnk, CAST(dense_rank() OVER w AS INTEGER) AS dense, CAST(ntile(4) OVER w AS INTEGER) AS quarter, round(percent_rank() OVER w,6)+0.0 AS pct FROM bo WINDOW w AS (PARTITION BY left_id ORDER BY o, right_id)")
def _(spark, d):
    w = Window.partitionBy("left_id").orderBy("o", "right_id")
    return both_ways(o_pairs(spark, d)).select("left_id", "right_id", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(w).alias("quarter"), r(F.percent_rank().over(w)).alias("pct"))


@query("discs_summary", f"WITH {Z}, {DISCS} {FLAT_SQL}")
def _(spark, d):
    return flat2(disc_clusters(spark, d))


@query("discs_edges", SQL["overlap_edges"])
def _(spark, d):
    # the same edges by way of the sound bound, which leaves out pairs before they are measured
    near = fuse.candidate_pairs(stored(disc_clusters(spark, d)), 2)
    return rounded(graph.edges(measures.measure_pairs(near, 2, ["o"])), "weight")


@query("discs_cliques", SQL["maximal_cliques"])
def _(spark, d):
    k = stored(disc_clusters(spark, d))
    found = stored(graph.edges(measures.measure_pairs(fuse.candidate_pairs(k, 2), 2, ["o"])), "edges")
    return cliques.maximal_cliques(found).select(F.concat_ws(",", F.transform("members", lambda v: v.cast("string"))).alias("members"), "size")


@query("discs_pairs", f"WITH {_DISC_O} SELECT left_id, right_id, round(o,6)+0.0 AS o, round(oh,6)+0.0 AS oh FROM o")
def _(spark, d):
    return o_pairs(spark, d).select("left_id", "right_id", r("o").alias("o"), r("oh").alias("oh"))


# fusion
@query("fuse_pair_d2", f"WITH {Z}, {fused_rows('flags')} SELECT left_id, right_id, n, round(m1,6)+0.0 AS m1, round(a,6)+0.0 AS a, round(b,6)+0.0 AS b, round(c,6)+0.0 AS c FROM f")
def _(spark, d):
    return pair_out(fuse.fuse_pair(pairs.all_pairs(stored(flags(spark, d)), ["dim", "n", "mean", "cov"])))


def pair_out(x: DataFrame) -> DataFrame:
    return x.select("left_id", "right_id", "n", r(F.element_at("mean", 1)).alias("m1"), *[r(F.element_at("cov", k + 1)).alias(v) for k, v in enumerate("abc")])


@query("fuse_pair_moments_d2", SQL["fuse_pair_d2"])
def _(spark, d):
    return pair_out(fuse.fuse_pair(pairs.all_pairs(stored(flags(spark, d)), ["dim", "n", "mean", "cov"]), "moments"))


_BY_FLAG = f"WITH {Z}, k AS (SELECT ascii(l_returnflag) AS id, count(*) AS n, avg(z1) AS m1, avg(z2) AS m2, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c FROM z GROUP BY 1) {FLAT_SQL}"
for _form in ("centred", "moments", "gaps"):

    @query({"centred": "fuse_groups_d2", "moments": "fuse_groups_moments_d2", "gaps": "fuse_groups_gaps_d2"}[_form], _BY_FLAG)
    def _(spark, d, form=_form):
        k = stored(flags(spark, d))
        groups = k.select(F.floor(F.col("cluster_id") / 1000).alias("group_id"), "cluster_id")
        return flat2(fuse.fuse_groups(k, groups, form).withColumn("cluster_id", F.col("group_id")))


@query("fuse_groups_moments_d4", f"WITH {Z}, k AS (SELECT ascii(l_returnflag) AS id, count(*) AS n, {_D4} FROM z GROUP BY 1) SELECT CAST(id AS BIGINT) AS group_id, CAST(n AS BIGINT) AS n, {_D4_OUT} FROM k")
def _(spark, d):
    k = stored(flags(spark, d, 4))
    return flat4(fuse.fuse_groups(k, k.select(F.floor(F.col("cluster_id") / 1000).alias("group_id"), "cluster_id"), "moments"), "group_id")


@query("fusion_parts_d2", f"WITH {Z}, {FLAGS}, t AS (SELECT id // 1000 AS g, sum(n) AS n, sum((n-1)*(a+c)) AS w FROM k GROUP BY 1), whole AS (SELECT ascii(l_returnflag) AS g, (var_samp(z1)+var_samp(z2)) AS tr FROM z GROUP BY 1) SELECT CAST(g AS BIGINT) AS group_id, round(w/(n-1),6)+0.0 AS trace_within, round(tr-w/(n-1),6)+0.0 AS trace_between FROM t JOIN whole USING (g)")
def _(spark, d):
    k = stored(flags(spark, d))
    x = fuse.fusion_parts(fuse.fuse_groups(k, k.select(F.floor(F.col("cluster_id") / 1000).alias("group_id"), "cluster_id")))
    return x.select("group_id", r("trace_within").alias("trace_within"), r("trace_between").alias("trace_between"))


@query("fuse_all", f"WITH {Z}, k AS (SELECT 1 AS id, count(*) AS n, avg(z1) AS m1, avg(z2) AS m2, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c FROM z) {FLAT_SQL}")
def _(spark, d):
    return flat2(fuse.fuse_by(suppliers(spark, d).withColumn("one", F.lit(1).cast("long")), ["one"]).withColumn("cluster_id", F.col("one")))


for _hint in ("merge", "shuffle_hash"):

    @query(f"fuse_groups_{_hint}", _BY_FLAG)
    def _(spark, d, hint=_hint):
        k = stored(flags(spark, d))
        groups = k.select(F.floor(F.col("cluster_id") / 1000).alias("group_id"), "cluster_id")
        return flat2(fuse.fuse_groups(k, groups, hint=hint).withColumn("cluster_id", F.col("group_id")))


@query("fuse_clusters_udaf", _BY_FLAG)
def _(spark, d):
    sqlfuncs.register(spark)
    stored(flags(spark, d)).createOrReplaceTempView("flag_clusters")
    return flat2(spark.sql("SELECT cluster_id, fused_n(f) AS n, fused_mean(f, 2) AS mean, fused_cov(f, 2) AS cov FROM (SELECT cluster_id DIV 1000 AS cluster_id, fuse_clusters(n, mean, cov) AS f FROM flag_clusters GROUP BY 1)"))


@query("fuse_mean", f"WITH {Z} SELECT CAST(ascii(l_returnflag) AS BIGINT) AS upper, CAST(count(*) AS BIGINT) AS n, round(avg(z1),6)+0.0 AS m1, round(avg(z2),6)+0.0 AS m2 FROM z GROUP BY 1")
def _(spark, d):
    x = fuse.fuse_mean(stored(flags(spark, d)).withColumn("upper", F.floor(F.col("cluster_id") / 1000)), ["upper"])
    return x.select("upper", "n", r(F.col("mean")[0]).alias("m1"), r(F.col("mean")[1]).alias("m2"))


@query("fuse_mean_d64", f"WITH {_EMB} SELECT CAST(i AS BIGINT) AS axis, round(avg(CAST(x AS DOUBLE)),6)+0.0 AS mean FROM e GROUP BY 1")
def _(spark, d):
    x = fuse.fuse_mean(stored(labels(spark, d, 64)).withColumn("one", F.lit(1)), ["one"])
    return x.select(F.posexplode("mean").alias("p", "v")).select((F.col("p") + 1).cast("long").alias("axis"), r("v").alias("mean"))


for _dim in (2, 4):

    @query(f"fusion_exactness_d{_dim}", f"WITH {Z} SELECT CAST(ascii(l_returnflag) AS BIGINT) AS upper, CAST(count(*) AS BIGINT) AS n, true AS exact FROM z GROUP BY 1")
    def _(spark, d, dim=_dim):
        z = [f"z{i + 1}" for i in range(dim)]
        direct = S.summarize_columns(scenarios.lineitem_z(spark, d, dim, ("l_returnflag",)), F.ascii("l_returnflag"), z).withColumn("upper", F.col("cluster_id"))
        fused = fuse.fuse_by(flags(spark, d, dim).withColumn("upper", F.floor(F.col("cluster_id") / 1000)), ["upper"])
        return fuse.fusion_residual(fused, direct, ["upper"]).select("upper", "n", (F.col("residual") < 1e-9).alias("exact"))


def region_models(spark, d):
    """D = 1 models of account balances: one for each nation (the owner), keyed by region."""
    cust = tables.read_table(spark, d, "customer", ["c_nationkey", "c_acctbal"])
    nation = tables.read_table(spark, d, "nation", ["n_nationkey", "n_regionkey"])
    rows = cust.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    return S.summarize_columns(rows, F.col("n_regionkey"), ["c_acctbal"], F.col("c_nationkey").cast("string"))


@query("federated_fuse_region", "SELECT CAST(n_regionkey AS BIGINT) AS cluster_id, CAST(count(*) AS BIGINT) AS n, round(avg(c_acctbal),4)+0.0 AS mean, round(var_samp(c_acctbal),2)+0.0 AS var FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def _(spark, d):
    return fuse.fuse_models(region_models(spark, d)).select("cluster_id", "n", r(F.col("mean")[0], 4).alias("mean"), r(F.col("cov")[0], 2).alias("var"))


@query("fuse_models_outer", "WITH c AS (SELECT c_nationkey AS k, count(*) AS n, avg(c_acctbal) AS m FROM customer GROUP BY 1), s AS (SELECT s_nationkey AS k, count(*) AS n, avg(s_acctbal) AS m FROM supplier GROUP BY 1) SELECT CAST(coalesce(c.k, s.k) AS BIGINT) AS cluster_id, CAST(coalesce(c.n,0)+coalesce(s.n,0) AS BIGINT) AS n, round((coalesce(c.n*c.m,0)+coalesce(s.n*s.m,0))/(coalesce(c.n,0)+coalesce(s.n,0)),4)+0.0 AS mean FROM c FULL JOIN s ON c.k = s.k")
def _(spark, d):
    of = lambda t, p: S.summarize_columns(tables.read_table(spark, d, t, [f"{p}_nationkey", f"{p}_acctbal"]), F.col(f"{p}_nationkey"), [f"{p}_acctbal"]).select("cluster_id", F.col("n").alias(f"n_{p}"), F.col("mean")[0].alias(f"m_{p}"))
    both = of("customer", "c").join(of("supplier", "s"), "cluster_id", "full_outer")
    n = F.coalesce("n_c", F.lit(0)) + F.coalesce("n_s", F.lit(0))
    total = F.coalesce(F.col("n_c") * F.col("m_c"), F.lit(0.0)) + F.coalesce(F.col("n_s") * F.col("m_s"), F.lit(0.0))
    return both.select("cluster_id", n.alias("n"), r(total / n, 4).alias("mean"))


_DOCS16 = "w AS (SELECT doc_id, lang, unnest(string_split_regex(lower(text), '[ \\t\\n\\x0B\\f\\r]+')) AS t FROM documents), c AS (SELECT doc_id, lang, CAST(('0x' || substr(md5(t),1,8)) AS BIGINT) % 16 AS axis, count(*) AS k FROM w WHERE t <> '' GROUP BY ALL), x AS (SELECT lang, axis, k * 1.0 / sum(k) OVER (PARTITION BY doc_id) AS share FROM c), docs AS (SELECT lang, count(DISTINCT doc_id) AS n FROM c GROUP BY 1)"


@query("federated_docs_lang", f"WITH {_DOCS16} SELECT lang, CAST(axis AS INTEGER) AS axis, CAST(n AS BIGINT) AS n, round(sum(sqrt(share))/n,6)+0.0 AS mean, round((sum(share)-n*(sum(sqrt(share))/n)*(sum(sqrt(share))/n))/(n-1),6)+0.0 AS var FROM x JOIN docs USING (lang) GROUP BY lang, axis, n")
def _(spark, d):
    # every source keeps its documents and shares clusters by language; owner and language stand in the cluster_id
    docs = tables.hashed_words(tables.read_table(spark, d, "documents", ["doc_id", "lang", "source", "text"]), 16, ("lang", "source"))
    lang = F.ascii("lang") * 1000 + F.ascii(F.substring("lang", 2, 1))
    local = S.summarize_vectors(docs, F.pmod(F.xxhash64("source"), F.lit(1 << 32)) * 1_000_000 + lang, "vec", 16)
    whole = stats.with_diagonal(fuse.fuse_models(local.withColumn("cluster_id", F.pmod("cluster_id", F.lit(1_000_000)))))
    name = F.concat(F.char(F.floor(F.col("cluster_id") / 1000)), F.char(F.pmod("cluster_id", F.lit(1000))))
    x = whole.select(name.alias("lang"), "n", F.posexplode(F.arrays_zip("mean", "diag")).alias("axis", "x"))
    return x.filter("x.mean > 0").select("lang", "axis", "n", r("x.mean").alias("mean"), r("x.diag").alias("var"))


@query("fraud_watch", "WITH v AS (SELECT user_id, value FROM events WHERE event_type = 'purchase' AND value IS NOT NULL AND isfinite(value)), g AS (SELECT count(*) AS n2, avg(value) AS m2, var_samp(value) AS s2 FROM v), u AS (SELECT user_id, count(*) AS n1, avg(value) AS m1, var_samp(value) AS s1 FROM v GROUP BY 1 HAVING count(*) > 2), f AS (SELECT user_id, n1, ln(2*(((n1-1)*s1+(n2-1)*s2+n1*n2/(n1+n2)*(m1-m2)*(m1-m2))/(n1+n2-1))/(s1+s2)) AS o FROM u, g) SELECT CAST(user_id AS BIGINT) AS user_id, CAST(n1 AS BIGINT) AS n, round(o,6)+0.0 AS o, o >= 0.65 AS apart FROM f")
def _(spark, d):
    # one user's purchases against everybody's: users whose cluster barely overlaps the common one are to be looked at
    ev = tables.read_table(spark, d, "events", ["user_id", "event_type", "value"]).filter("event_type = 'purchase'")
    users = S.summarize_columns(ev, F.col("user_id"), ["value"]).filter("n > 2")
    common = stored(S.summarize_columns(ev, F.lit(-1), ["value"])).select("model_id", F.struct("n", "mean", "cov").alias("q"))
    both = users.select("model_id", F.col("cluster_id").alias("left_id"), F.struct("n", "mean", "cov").alias("p")).join(F.broadcast(common), "model_id").withColumn("right_id", F.lit(-1).cast("long"))
    x = measures.measures1(both, ["o"])
    return x.select(F.col("left_id").alias("user_id"), F.col("n1").alias("n"), r("o").alias("o"), (F.col("o") >= 0.65).alias("apart"))


@query("fuse_overlapping", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_CLIQUES}, {_GROUPS}, f AS (SELECT grp.group_id, count(*) AS n, avg(z1) AS m1, avg(z2) AS m2, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c FROM z JOIN dk ON (z1-x)*(z1-x)+(z2-y)*(z2-y) <= r*r JOIN grp ON grp.cluster_id = dk.disc GROUP BY 1), mem AS (SELECT group_id, string_agg(CAST(cluster_id AS VARCHAR), ',' ORDER BY cluster_id) AS members FROM grp GROUP BY 1) SELECT group_id, members, CAST(n AS BIGINT) AS n, round(m1,6)+0.0 AS m1, round(m2,6)+0.0 AS m2, round(a,6)+0.0 AS a, round(b,6)+0.0 AS b, round(c,6)+0.0 AS c FROM f JOIN mem USING (group_id)")
def _(spark, d):
    x = fuse.fuse_overlapping(stored(disc_clusters(spark, d)), dim=2).withColumn("members", F.concat_ws(",", F.transform("members", lambda v: v.cast("string"))))
    return flat2(x.withColumn("cluster_id", F.col("group_id"))).withColumnRenamed("cluster_id", "group_id").join(x.select("group_id", "members"), "group_id")


@query("fused_count_conserved", f"WITH {Z}, {DISCS} SELECT CAST(sum(n) AS BIGINT) AS n FROM k")
def _(spark, d):
    return fuse.fuse_overlapping(stored(disc_clusters(spark, d)), dim=2).agg(F.sum("n").alias("n"))


@query("fuse_overlapping_rounds")
def _(spark, d):
    return fuse.fuse_overlapping(stored(disc_clusters(spark, d)), rounds=3, dim=2).select("group_id", "n", "members")


@query("fuse_iterative", f"WITH RECURSIVE {Z}, {FLAGS}, {iterated(BEST_PAIR)} SELECT CAST(id AS BIGINT) AS cluster_id, CAST(n AS BIGINT) AS n, array_to_string(members, ',') AS members FROM step WHERE round = (SELECT max(round) FROM step)")
def _(spark, d):
    return fuse.fuse_iterative(flags(spark, d))[0].select("cluster_id", "n", F.concat_ws(",", F.transform("members", lambda v: v.cast("string"))).alias("members"))


# made pairs leave c clusters; the new ones are measured against the others and against each other
_COUNTED = f"{iterated(MUTUAL_PAIRS)}, sizes AS (SELECT round, count(*) AS c, lag(count(*)) OVER (ORDER BY round) - count(*) AS made FROM step GROUP BY 1)"


@query("fuse_one_step_vs_iterative", f"WITH RECURSIVE {_DISC_O}, {_EDGE}, {_CLIQUES}, {_GROUPS}, {_COUNTED} SELECT CAST((SELECT count(DISTINCT group_id) FROM grp) AS BIGINT) AS one_step_clusters, CAST(min(c) AS BIGINT) AS iterative_clusters, CAST(1 AS INTEGER) AS one_step_rounds, CAST(max(c)*(max(c)-1)//2 AS INTEGER) AS one_step_pairs, CAST(count(*) AS INTEGER) AS iterative_rounds, CAST(max(c)*(max(c)-1)//2+coalesce(sum(made*(c-made)+made*(made-1)//2),0) AS INTEGER) AS iterative_pairs FROM sizes")
def _(spark, d):
    k = stored(disc_clusters(spark, d))
    n = k.count()
    out, counts = fuse.fuse_iterative(k, rounds="mutual")
    one = fuse.fuse_overlapping(k, dim=2)
    return one.agg(F.count(F.lit(1)).alias("one_step_clusters")).crossJoin(out.agg(F.count(F.lit(1)).alias("iterative_clusters"))).select("*", F.lit(1).alias("one_step_rounds"), F.lit(n * (n - 1) // 2).alias("one_step_pairs"), F.lit(counts["rounds"]).alias("iterative_rounds"), F.lit(counts["pairs"]).alias("iterative_pairs"))


@query("clusters_json_roundtrip", f"WITH {Z}, {FLAGS} {FLAT_SQL}")
def _(spark, d):
    return flat2(exchange.clusters_from_json(exchange.clusters_to_json(flags(spark, d))))


# scenarios and experiments
for _s in scenarios.NAMES:

    @query({"a": "scenario_a_d2", "b": "scenario_b_d2"}.get(_s, f"scenario_{_s}_d2"), f"WITH {Z}, {SCENARIO_K}, k AS (SELECT * FROM sk WHERE scenario = '{_s}'), {PAIRS} SELECT '{_s}' AS scenario, {_ALL} FROM y")
    def _(spark, d, name=_s):
        k = stored(scenarios.scenario_clusters(spark, d).filter(F.col("model_id") == name))
        x = measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), 2, literal=True)
        return rounded(x.select(F.col("model_id").alias("scenario"), *measures.MEASURES), *measures.MEASURES)




@query("scenario_grid_d2", f"WITH {Z}, {SCENARIO_K}, k AS (SELECT * FROM sk), {PAIRS.replace('ON p.id < q.id', 'ON p.id < q.id AND p.scenario = q.scenario').replace('p.id AS left_id', 'p.scenario AS scenario, p.id AS left_id')} SELECT scenario, {_ALL} FROM y")
def _(spark, d):
    x = measures.measure_pairs(pairs.all_pairs(stored(scenarios.scenario_clusters(spark, d)), ["n", "mean", "cov"]), 2, literal=True)
    long = x.unpivot(["model_id"], measures.MEASURES, "measure", "value").select(F.lit(2).alias("dim"), F.col("model_id").alias("scenario"), "measure", r("value").alias("value"))
    return experiment.grid(long).drop("dim")


@query("scenario_box_counts", "SELECT CAST(count(*) AS BIGINT) AS n FROM lineitem WHERE l_quantity BETWEEN 23 AND 28 AND l_extendedprice BETWEEN 47000 AND 59000")
def _(spark, d):
    return tables.read_table(spark, d, "lineitem", ["l_quantity", "l_extendedprice"]).filter(F.col("l_quantity").between(23, 28) & F.col("l_extendedprice").between(47000, 59000)).agg(F.count(F.lit(1)).alias("n"))


@query("scenario_one_scan", "SELECT CAST(count(*) FILTER (WHERE l_quantity <= 10 AND l_extendedprice <= 25000) AS BIGINT) AS n_low, CAST(count(*) FILTER (WHERE l_quantity >= 41 AND l_extendedprice >= 80000) AS BIGINT) AS n_high, round(avg(l_quantity) FILTER (WHERE l_quantity <= 10 AND l_extendedprice <= 25000),6)+0.0 AS q_low FROM lineitem")
def _(spark, d):
    li = tables.read_table(spark, d, "lineitem", ["l_quantity", "l_extendedprice"])
    low, high = (F.col("l_quantity") <= 10) & (F.col("l_extendedprice") <= 25000), (F.col("l_quantity") >= 41) & (F.col("l_extendedprice") >= 80000)
    return li.agg(F.count_if(low).alias("n_low"), F.count_if(high).alias("n_high"), r(F.avg(F.when(low, F.col("l_quantity")))).alias("q_low"))


_BY_SCENARIO = PAIRS.replace("ON p.id < q.id", "ON p.id < q.id AND p.scenario = q.scenario").replace("p.id AS left_id", "p.scenario AS scenario, p.id AS left_id")
_RESULTS = (
    f"{Z}, {SCENARIO_K}, k AS (SELECT * FROM sk), {_BY_SCENARIO}, l AS (" + " UNION ALL ".join(f"SELECT scenario AS name, '{m}' AS measure, {MEASURE_SQL[m]} AS value FROM y" for m in measures.MEASURES) + "), "
    "variants(name, variant) AS (VALUES ('a','narrow'), ('a','wide'), ('b','narrow'), ('b','wide'), ('c_tight','narrow'), ('d_axis','narrow'), ('c_loose','wide'), ('d_diag','wide')), "
    "p AS (SELECT CAST(2 AS INTEGER) AS dim, variant, name[1] AS scenario, measure, value FROM l JOIN variants USING (name))"
)
_VARIANT = "dim", "variant", "measure"


@query("detection_flags", f"WITH {_RESULTS}, v AS (SELECT *, max(value) FILTER (WHERE scenario='a') OVER w AS va, max(value) FILTER (WHERE scenario='b') OVER w AS vb, max(value) FILTER (WHERE scenario='c') OVER w AS vc, max(value) FILTER (WHERE scenario='d') OVER w AS vd FROM p WINDOW w AS (PARTITION BY dim, variant, measure)) SELECT dim, variant, scenario, measure, CASE WHEN scenario IN ('a','b') THEN va < vb WHEN scenario = 'c' THEN vc < least(vb, vd) ELSE vd > greatest(va, vc) END AS correct FROM v")
def _(spark, d):
    return experiment.detections(experiment.table_results(spark, d), _VARIANT).select("dim", "variant", "scenario", "measure", "correct")


@query("detection_counts", f"SELECT measure, CAST(count(*) FILTER (WHERE correct) AS BIGINT) AS n_correct FROM ({SQL['detection_flags']}) GROUP BY measure")
def _(spark, d):
    return experiment.detections(experiment.table_results(spark, d), _VARIANT).groupBy("measure").agg(F.count_if(F.col("correct")).alias("n_correct"))


@query("time_multiple", "WITH p AS (SELECT 1 AS dim, event_type AS scenario, strftime(ts, '%H') AS measure, nullif(epoch_us(max(ts)) - epoch_us(min(ts)), 0) / nullif(count(*) - 1, 0) AS micros FROM events GROUP BY ALL) SELECT CAST(dim AS INTEGER) AS dim, scenario, measure, round(micros / min(micros) OVER (PARTITION BY dim, scenario),4)+0.0 AS multiple FROM p")
def _(spark, d):
    return experiment.multiples(experiment.event_paces(tables.events(spark, d))).select("dim", "scenario", "measure", r("multiple", 4).alias("multiple"))


@query("separability_gap", f"WITH {_RESULTS} SELECT dim, variant, measure, round(min(value) FILTER (WHERE scenario IN ('b','d')) - max(value) FILTER (WHERE scenario IN ('a','c')),6)+0.0 AS gap FROM p GROUP BY 1, 2, 3")
def _(spark, d):
    return rounded(experiment.separability(experiment.table_results(spark, d), _VARIANT), "gap")


@query("scenario_generated_d100")
def _(spark, d):
    k = scenarios.generated_clusters(spark, 100)
    x = measures.measure_pairs(pairs.all_pairs(stored(k), ["n", "mean", "cov"]), 100)
    long = x.unpivot(["model_id"], measures.MEASURES, "measure", "value").select(F.lit(100).alias("dim"), F.col("model_id").alias("scenario"), "measure", "value")
    return experiment.detections(long)


@query("pair_grid")
def _(spark, d):
    return experiment.run_pair_grid(spark, dims=(2, 4), reps=5, sf_dir=d)


@query("generated_verdicts")
def _(spark, d):
    k = [scenarios.generated_clusters(spark, dim) for dim in (2, 100)]
    long = [measures.measure_pairs(pairs.all_pairs(stored(x), ["n", "mean", "cov"]), dim).unpivot(["model_id"], measures.MEASURES, "measure", "value").select(F.lit(dim).alias("dim"), F.col("model_id").alias("scenario"), "measure", "value") for x, dim in zip(k, (2, 100))]
    return experiment.compared_with_published(long[0].union(long[1]))


@query("cost_model", "WITH f AS (SELECT CAST(d AS INTEGER) AS dim, m AS measure, CAST(CASE m WHEN 'js' THEN 2*(d*d*d/3) + 4*d*d*d WHEN 'w' THEN 2*(9*d*d*d) + 4*d*d*d WHEN 'oh' THEN 8*d WHEN 'vr' THEN d*d*d/3 + 3*d*d WHEN 'o' THEN d*d*d/3 + 3*d*d ELSE d*d*d/3 + 2*d*d + d*d END AS DOUBLE) AS flops FROM (SELECT unnest([1, 2, 4, 16, 64, 100])::DOUBLE AS d), (SELECT unnest(['b', 'js', 'w', 'vr', 'ab', 'o', 'oh']) AS m)), k AS (SELECT CAST(count(DISTINCT l_suppkey) * (count(DISTINCT l_suppkey) - 1) // 2 AS BIGINT) AS n_pairs FROM lineitem) SELECT dim, measure, flops, n_pairs, flops * n_pairs AS total FROM f, k")
def _(spark, d):
    return experiment.cost_model(tables.read_table(spark, d, "lineitem", ["l_suppkey"]))


# streams and time
_DAY = "SELECT event_type, date_trunc('day', ts) AS start, date_trunc('day', ts) + INTERVAL 1 DAY AS \"end\", CAST(count(*) AS BIGINT) AS n, round(avg(value),6)+0.0 AS mean, round(coalesce(var_samp(value),0),4)+0.0 AS var FROM events WHERE value IS NOT NULL AND isfinite(value) GROUP BY 1, 2"


def plain_times(x: DataFrame, k: int = 4) -> DataFrame:
    return x.select(*[F.col(c).cast("timestamp_ntz").alias(c) if c in ("start", "end") else r(c).alias(c) if c == "mean" else r(c, k).alias(c) if c == "var" else F.col(c) for c in x.columns])


@query("stream_tumbling_batch", _DAY)
def _(spark, d):
    return plain_times(summaries.window_summaries(tables.events(spark, d)))


@query("stream_sliding_batch", "WITH x AS (SELECT event_type, value, date_trunc('day', ts) - INTERVAL (k) DAY AS start FROM events, range(0, 2) t(k) WHERE value IS NOT NULL AND isfinite(value)) SELECT event_type, start, start + INTERVAL 2 DAY AS \"end\", CAST(count(*) AS BIGINT) AS n, round(avg(value),6)+0.0 AS mean, round(coalesce(var_samp(value),0),4)+0.0 AS var FROM x GROUP BY 1, 2")
def _(spark, d):
    return plain_times(summaries.window_summaries(tables.events(spark, d), "2 days", "1 day"))


@query("stream_session_batch", "WITH g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WHERE value IS NOT NULL AND isfinite(value)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS \"end\", CAST(count(*) AS BIGINT) AS n, round(avg(value),6)+0.0 AS mean, round(coalesce(var_samp(value),0),6)+0.0 AS var FROM s GROUP BY user_id, k")
def _(spark, d):
    return plain_times(summaries.session_summaries(tables.events(spark, d)), 6)


def day_models(ev: DataFrame) -> DataFrame:
    x = summaries.window_summaries(ev)
    return x.select("event_type", F.col("end").alias("valid_from"), (F.col("end") + F.expr("interval 1 day")).alias("valid_to"), "n", "mean", "var")


@query("asof_model_events", f"WITH m AS ({_DAY}) SELECT e.event_id, m.n AS model_n FROM events e ASOF LEFT JOIN m ON e.event_type = m.event_type AND e.ts >= m.\"end\"")
def _(spark, d):
    ev = tables.events(spark, d).select("event_id", "event_type", "ts")
    return summaries.asof(ev, day_models(tables.events(spark, d)), "event_type").select("event_id", F.col("snap_n").alias("model_n"))


@query("interval_model_events", f"WITH m AS ({_DAY}) SELECT e.event_id, m.n AS model_n FROM events e JOIN m ON e.event_type = m.event_type AND e.ts >= m.\"end\" AND e.ts < m.\"end\" + INTERVAL 1 DAY")
def _(spark, d):
    ev = tables.events(spark, d)
    return summaries.within_validity(ev.select("event_id", "event_type", "ts"), day_models(ev), "event_type").select("event_id", F.col("n").alias("model_n"))


@query("drift_lag_events", f"WITH m AS ({_DAY}) SELECT event_type, start, round(mean - lag(mean) OVER (PARTITION BY event_type ORDER BY start),6)+0.0 AS drift, round(lead(mean) OVER (PARTITION BY event_type ORDER BY start),6)+0.0 AS next FROM m")
def _(spark, d):
    w = Window.partitionBy("event_type").orderBy("start")
    x = plain_times(summaries.window_summaries(tables.events(spark, d)))
    return x.select("event_type", "start", r(F.col("mean") - F.lag("mean").over(w), 6).alias("drift"), r(F.lead("mean").over(w), 6).alias("next"))


@query("running_summary", f"WITH m AS ({_DAY}) SELECT event_type, start, CAST(sum(n) OVER w AS BIGINT) AS n, round(sum(n*mean) OVER w / sum(n) OVER w,5)+0.0 AS mean FROM m WINDOW w AS (PARTITION BY event_type ORDER BY start ROWS UNBOUNDED PRECEDING)")
def _(spark, d):
    w = Window.partitionBy("event_type").orderBy("start").rowsBetween(Window.unboundedPreceding, 0)
    x = plain_times(summaries.window_summaries(tables.events(spark, d)))
    return x.select("event_type", "start", F.sum("n").over(w).alias("n"), r(F.sum(F.col("n") * F.col("mean")).over(w) / F.sum("n").over(w), 5).alias("mean"))


@query("trailing_summary", f"WITH m AS ({_DAY}) SELECT event_type, start, CAST(sum(n) OVER w AS BIGINT) AS n FROM m WINDOW w AS (PARTITION BY event_type ORDER BY start RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW)")
def _(spark, d):
    x = plain_times(summaries.window_summaries(tables.events(spark, d))).withColumn("day", F.datediff("start", F.lit("2000-01-01").cast("date")))
    w = Window.partitionBy("event_type").orderBy("day").rangeBetween(-6, 0)
    return x.select("event_type", "start", F.sum("n").over(w).alias("n"))


@query("embedding_prefix", "SELECT vec_id, round(list_sum(list_transform(embedding[1:8], lambda x: CAST(x AS DOUBLE)*x)),5)+0.0 AS energy, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS n_positive FROM embeddings")
def _(spark, d):
    e = tables.read_table(spark, d, "embeddings", ["vec_id", "embedding"])
    energy = F.aggregate(F.slice("embedding", 1, 8), F.lit(0.0), lambda s, x: s + x.cast("double") * x)
    return e.select("vec_id", r(energy, 5).alias("energy"), F.size(F.filter("embedding", lambda x: x > 0)).alias("n_positive"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem clusters by flag and status, overlapping ones fused in one step."""
    ship(spark)
    return fuse.fuse_overlapping(stored(flags(spark, sf_dir)), dim=2)
