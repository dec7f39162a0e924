"""Shards by a keyed permutation of global row numbers (rows law).

Rows get a global number 0..N-1 from their identity, not from their place in the files. A mixed-radix Feistel
network over a x b >= N permutes the numbers; results at or beyond N walk the cycle until they fall below N.
Position p then lies in shard p mod S at slot p div S, so shard sizes differ by one row at most, slots are gapless,
and ``row_number_at`` inverts the map: which row stands at a shard and slot is computed, not looked up.

Nulls: a null text has size 8 and the checksum of no bytes; a null doc_id is an id like any other.
Repeated rows are counted first (one shuffled row for each distinct one) and each copy gets a position of its own.
An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import CRC_TABLE, crc_sql, store, table

#: Buckets that rows are numbered in, at least, and rows of a bucket, about, where there are more rows than these hold.
BUCKETS, BUCKET_ROWS = 4096, 1_000_000
#: Copies of one repeated row that are numbered in one array.
COPIES = 10_000
SHARDS, KEY = 24, 20240229
ROUNDS = 6
#: Steps of cycle walking that are unrolled. a*b-N < a ~ sqrt(N), so a walk is at most a*b-N+1 long, and for N > 64**2
#: one of more than 64 steps has a chance below (1/64)**64; such a row raises an error rather than be misplaced.
WALK = 64


def radices(n: int) -> tuple[int, int]:
    a = math.isqrt(max(n - 1, 0)) + 1
    return a, max(1, -(-n // a))


def _number(text: Column) -> Column:
    """60 bits of the md5 of a text: a hash that every engine has, so that shards can be recomputed elsewhere."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def _mix(half: Column, r: int, key: int, radix: int) -> Column:
    return F.pmod(_number(F.concat(F.lit(f"{key},{r},"), half.cast("string"))), F.lit(radix))


def _parts(x: Column, b: int) -> tuple[Column, Column]:
    return F.call_function("div", x, F.lit(b)), F.pmod(x, F.lit(b))


def _forward(x: Column, n: int, key: int) -> Column:
    a, b = radices(n)
    left, right = _parts(x, b)
    for r in range(ROUNDS):
        if r % 2 == 0:
            left = F.pmod(left + _mix(right, r, key, a), F.lit(a))
        else:
            right = F.pmod(right + _mix(left, r, key, b), F.lit(b))
    return left * F.lit(b) + right


def _backward(y: Column, n: int, key: int) -> Column:
    a, b = radices(n)
    left, right = _parts(y, b)
    for r in reversed(range(ROUNDS)):
        if r % 2 == 0:
            left = F.pmod(left - _mix(right, r, key, a), F.lit(a))
        else:
            right = F.pmod(right - _mix(left, r, key, b), F.lit(b))
    return left * F.lit(b) + right


def _walked(x: Column, n: int, key: int, step) -> Column:
    a, b = radices(n)
    first = step(x, n, key)
    steps = min(WALK, a * b - n)
    if not steps:
        return first
    walked = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), first, lambda y, _: F.when(y < n, y).otherwise(step(y, n, key)))
    return F.when(walked < n, walked).otherwise(F.raise_error(F.lit("cycle walk did not end")).cast("long"))


def permuted(x: Column, n: int, key: int = 0) -> Column:
    """Position of global row number ``x`` (long) in the keyed shuffle of n rows."""
    return _walked(x.cast("long"), n, key, _forward)


def row_number_at(shard: Column, slot: Column, n: int, shards: int, key: int = 0) -> Column:
    """Global row number that stands at (shard, slot): the inverse of ``permuted``."""
    return _walked((slot * F.lit(shards) + shard).cast("long"), n, key, _backward)


def numbered(df: DataFrame, identity: list[str]) -> tuple[DataFrame, int]:
    """Rows of ``identity`` columns with ``row_number`` 0..N-1, in an order that only their values decide; and N."""
    counted = store(df.groupBy(*identity).agg(F.count(F.lit(1)).alias("copies")), "shard-rows")
    rows, n = counted.agg(F.count(F.lit(1)), F.coalesce(F.sum("copies"), F.lit(0))).first()
    buckets = max(BUCKETS, -(-rows // BUCKET_ROWS))
    named = F.concat_ws(",", *[F.coalesce(F.col(c).cast("string"), F.lit("null")) for c in identity])
    counted = counted.withColumn("bucket", F.pmod(_number(named), F.lit(buckets)))
    # a row for each bucket: one task adds them up, and they may be broadcast (a million rows a bucket: 10**11 rows make 10**5)
    sizes = counted.groupBy("bucket").agg(F.sum("copies").alias("rows"))
    before = sizes.select("bucket", (F.sum("rows").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)) - F.col("rows")).alias("before"))
    inside = Window.partitionBy("bucket").orderBy(*identity).rowsBetween(Window.unboundedPreceding, 0)
    first = counted.withColumn("first", F.sum("copies").over(inside) - F.col("copies")).join(F.broadcast(before), "bucket")
    # copies are counted out in stretches, so that no row holds an array of all of them
    stretches = first.select(*identity, "copies", (F.col("before") + F.col("first")).alias("start"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1, F.lit(COPIES).cast("long"))).alias("at"))
    each = F.explode(F.sequence(F.col("start") + F.col("at"), F.col("start") + F.least(F.col("at") + COPIES, F.col("copies")) - 1))
    return stretches.select(*identity, each.alias("row_number")), n


def shard_rows(docs: DataFrame, shards: int = SHARDS, key: int = KEY) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot for each row of ``docs`` (doc_id, text)."""
    body = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(body) + F.lit(8)).cast("long").alias("size"), F.crc32(body.cast("binary")).alias("text_crc32"))
    placed, n = numbered(rows, ["doc_id", "size", "text_crc32"])
    placed = placed.withColumn("position", permuted(F.col("row_number"), max(n, 1), key))
    shard = F.pmod(F.col("position"), F.lit(shards))
    return placed.select("doc_id", "size", "text_crc32", shard.cast("int").alias("shard"), F.call_function("div", F.col("position"), F.lit(shards).cast("long")).alias("slot"))


def write_shards(docs: DataFrame, path: str, shards: int = SHARDS, key: int = KEY) -> None:
    """Write ``docs`` (distinct doc_id) as one folder for each shard, rows in slot order."""
    placed = shard_rows(docs, shards, key).select("doc_id", "shard", "slot")
    (docs.join(placed, "doc_id").repartition(shards, "shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path))


def query(spark, sf_dir):
    out = shard_rows(table(spark, sf_dir, "documents", "doc_id", "text"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def _rounds_sql(x: str) -> str:
    """Columns l0, r0, l1, ... of the rounds over the number ``x``, and p, the result."""
    out = [f"{x} // b AS l0, {x} % b AS r0"]
    for r in range(ROUNDS):
        number = lambda half: f"CAST('0x' || substr(md5('{KEY},{r},' || CAST({half} AS VARCHAR)), 1, 15) AS BIGINT)"  # noqa: B023, E731
        if r % 2 == 0:
            out.append(f"(l{r} + {number(f'r{r}')} % a) % a AS l{r + 1}, r{r} AS r{r + 1}")
        else:
            out.append(f"l{r} AS l{r + 1}, (r{r} + {number(f'l{r}')} % b) % b AS r{r + 1}")
    return ", ".join([*out, f"l{ROUNDS} * b + r{ROUNDS} AS p"])


#: The whole map from its definition: numbering by value, rounds, walks.
ORACLE_SQL = f"""
WITH RECURSIVE {CRC_TABLE},
d AS (SELECT doc_id, CAST(octet_length(encode(coalesce(text, ''))) + 8 AS BIGINT) AS size, CAST({crc_sql("coalesce(text, '')")} AS BIGINT) AS text_crc32 FROM documents, tab),
k AS (SELECT CAST(count(*) AS BIGINT) AS n, CAST(floor(sqrt(greatest(count(*) - 1, 0))) AS BIGINT) + 1 AS a, greatest({BUCKETS}, CAST(ceil((SELECT count(*) FROM (SELECT DISTINCT * FROM d)) / {BUCKET_ROWS}.0) AS BIGINT)) AS buckets FROM d),
c AS (SELECT *, greatest(1, CAST(ceil(n / a) AS BIGINT)) AS b FROM k),
x AS (SELECT d.*, row_number() OVER (ORDER BY CAST('0x' || substr(md5(concat_ws(',', coalesce(CAST(doc_id AS VARCHAR), 'null'), CAST(size AS VARCHAR), CAST(text_crc32 AS VARCHAR))), 1, 15) AS BIGINT) % buckets, doc_id NULLS FIRST, size, text_crc32) - 1 AS x FROM d, c),
walk(doc_id, size, text_crc32, y) AS (
  SELECT doc_id, size, text_crc32, p FROM (SELECT doc_id, size, text_crc32, {_rounds_sql("x")} FROM x, c)
  UNION ALL SELECT doc_id, size, text_crc32, p FROM (SELECT doc_id, size, text_crc32, {_rounds_sql("y")} FROM walk, c WHERE y >= n))
SELECT doc_id, size, text_crc32, 'rows' AS law, CAST(y % {SHARDS} AS INTEGER) AS shard, CAST(y // {SHARDS} AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard FROM walk, c WHERE y < n
"""
