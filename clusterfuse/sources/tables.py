"""Readers with pruned columns, scratch tables, and the feature sets of the given tables."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir as the session has it; a local folder only where it is unset and Spark runs in one process."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    own = os.path.join(tempfile.gettempdir(), "checkpoints")
    spark.sparkContext.setCheckpointDir(own)
    return own


def store(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a Parquet table of the shared folder, read back; removed when the JVM ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def discard(*tables: DataFrame | None) -> None:
    """Remove stored tables that nothing reads any more; other frames and None are passed over."""
    for df in tables:
        if path := getattr(df, "_stored_at", None):
            where = df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events with ts as a timestamp (watermarks need one), k from the JSON props and the hour."""
    e = read_table(spark, sf_dir, "events")
    return e.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("double")).withColumn("hour", F.hour("ts").cast("double"))


def hashed_words(docs: DataFrame, buckets: int = 100, keys: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """``keys`` and vec: square roots of the shares of words in md5 buckets, counted inside the row, so that nothing is shuffled.

    Rows without words have no vector and are left out."""
    words = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    bucket = lambda w: (F.conv(F.substring(F.md5(w.cast("binary")), 1, 8), 16, 10).cast("long") % buckets).cast("int")
    # one mark of each bucket among the sorted buckets of the words: the distance of two marks tells how many lie between
    marked = F.sort_array(F.concat(F.transform(words, bucket), F.sequence(F.lit(0), F.lit(buckets - 1))))

    def shares(m: Column) -> Column:
        at = F.concat(F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda i: F.array_position(m, i)), F.array((F.size(m) + 1).cast("long")))
        total = (F.size(m) - buckets).cast("double")
        counted = F.transform(F.array(at), lambda a: F.transform(F.sequence(F.lit(1), F.lit(buckets)), lambda i: F.sqrt((F.element_at(a, i + 1) - F.element_at(a, i) - 1) / total)))
        return F.when(total > 0, F.element_at(counted, 1))

    return docs.select(*keys, F.element_at(F.transform(F.array(marked), shares), 1).alias("vec")).filter("vec is not null")
