"""Shared helpers: text expressions, scratch tables in the shared folder, readers."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import let
from ..sources import tables

__all__ = ["BLANK", "CRC_TABLE", "LOWER", "UPPER", "WORD_BREAK", "ascii_lower", "blank_words", "crc_sql", "few", "let", "plain_words", "release", "scope", "store", "table", "text_key", "unused", "without_rows", "without_texts"]
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Everything that is not a digit, an ASCII letter or a character beyond ASCII; applied to lower-cased text.
WORD_BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: ASCII white space.
BLANK = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return tables.read_table(spark, sf_dir, name, list(columns) or None)


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only. Pure ASCII text takes the fast path; null stays null."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def plain_words(text: Column) -> Column:
    """Lower-cased words of letters, digits and characters beyond ASCII; null and empty give an empty array."""
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), WORD_BREAK), "")


def blank_words(text: Column, lower: bool = False) -> Column:
    """Words between ASCII white space; null and empty give an empty array."""
    whole = F.coalesce(text, F.lit(""))
    return F.array_remove(F.split(ascii_lower(whole) if lower else whole, BLANK), "")


_scratch: dict[str, list[str]] = {}
_scope = ""


@contextmanager
def scope(name: str):
    """Scratch tables that are stored inside are listed under ``name``, so that ``release`` can remove them."""
    global _scope
    before, _scope = _scope, name
    try:
        yield
    finally:
        _scope = before


def release(spark: SparkSession, name: str) -> None:
    """Remove the scratch tables of a scope whose results have been written."""
    for path in _scratch.pop(name, []):
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def store(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as a Parquet table in the shared folder and read it back: cuts lineage and survives lost executors.

    The table is removed when the JVM ends, or by ``release`` of the scope that it was stored in."""
    out = tables.store(df, name)
    if _scope:
        _scratch.setdefault(_scope, []).append(out._stored_at)
    return out


def unused(columns: list[str], name: str) -> str:
    """``name``, with as many underscores before it as make it differ from all ``columns``, in any case of letters."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


#: Ids or keys that may be broadcast; beyond that Spark shuffles both sides.
FEW = 500_000


def few(df: DataFrame) -> DataFrame:
    """Broadcast ``df``, a stored list of ids or keys, if its count allows that."""
    return F.broadcast(df) if df.limit(FEW + 1).count() <= FEW else df


def text_key() -> list[Column]:
    """text_hash and text_crc: 96 bits that tell texts apart, so that a text is known again without its row."""
    body = F.coalesce(F.col("text"), F.lit(""))
    return [F.xxhash64(body).alias("text_hash"), F.crc32(body.cast("binary")).alias("text_crc")]


def _keyed(docs: DataFrame) -> tuple[DataFrame, list[str]]:
    """``docs`` with doc_id as a long, text_hash and text_crc under names that no column of the caller has."""
    names = [unused(docs.columns, c) for c in ("key_doc_id", "key_text_hash", "key_text_crc")]
    return docs.withColumns(dict(zip(names, [F.col("doc_id").cast("long"), *text_key()]))), names


def without_texts(docs: DataFrame, texts: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose text is not among ``texts`` (text_hash, text_crc): a verdict on a text holds for every row that has it, with an id or without."""
    keyed, names = _keyed(docs)
    gone = store(texts.select(F.col("text_hash").alias(names[1]), F.col("text_crc").alias(names[2])).distinct(), "gone")
    return keyed.join(few(gone), names[1:], "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])


def without_rows(docs: DataFrame, gone: DataFrame, again: DataFrame) -> DataFrame:
    """``docs`` without the rows of ``gone`` and with one each of those of ``again``; both are doc_id, text_hash, text_crc, and null ids are equal."""
    keyed, names = _keyed(docs)
    columns = [F.col(f"`{c}`") for c in docs.columns]

    def joined(df: DataFrame, keys: DataFrame, how: str) -> DataFrame:
        k = few(keys.select(*[F.col(c).alias(f"of_{n}") for c, n in zip(("doc_id", "text_hash", "text_crc"), names)]))
        on = F.lit(True)
        for n in names:
            on = on & F.col(n).eqNullSafe(F.col(f"of_{n}"))
        return df.join(k, on, how)

    rest = joined(keyed, gone, "left_anti")
    if again.isEmpty():
        return rest.select(*columns)
    once = joined(rest, again, "left_semi").dropDuplicates(names)
    return joined(rest, again, "left_anti").select(*columns).union(once.select(*columns))


#: DuckDB SQL: a CTE with the 256 steps of the checksum, made from its rule, and the unsigned crc32 of a text's UTF-8 bytes by it.
CRC_TABLE = "tab AS (SELECT list_transform(range(256), lambda i: list_reduce([i, 0, 0, 0, 0, 0, 0, 0, 0], lambda x, y: xor(x >> 1, 3988292384 * (x & 1)))) AS crc_step)"


def crc_sql(text: str) -> str:
    return f"xor(list_reduce(list_concat([4294967295], list_transform(regexp_extract_all(hex(encode({text})), '..'), lambda x: CAST('0x' || x AS BIGINT))), lambda c, b: xor(crc_step[(xor(c, b) & 255) + 1], c >> 8)), 4294967295)"
