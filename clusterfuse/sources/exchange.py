"""Sources and sinks of clusters: Parquet by model, JSON for exchange between owners, CSV of results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.summarize import CLUSTER


def write_clusters(df: DataFrame, path: str, mode: str = "errorifexists") -> None:
    df.write.mode(mode).partitionBy("model_id").parquet(path)


def read_clusters(spark: SparkSession, path: str, model_id: str | None = None) -> DataFrame:
    """Clusters under ``path``; one model reads its own folder only."""
    df = spark.read.schema(CLUSTER).parquet(path)
    return df if model_id is None else df.filter(F.col("model_id") == model_id)


def clusters_to_json(clusters: DataFrame) -> DataFrame:
    return clusters.select(F.to_json(F.struct(*clusters.columns)).alias("json"))


def clusters_from_json(rows: DataFrame) -> DataFrame:
    return rows.select(F.from_json("json", CLUSTER).alias("c")).select("c.*")


def write_results_csv(results: DataFrame, path: str) -> None:
    """Results as CSV; arrays become comma-joined text."""
    flat = [F.concat_ws(",", c).alias(c) if kind.startswith("array") else F.col(c) for c, kind in results.dtypes]
    results.select(*flat).write.option("header", True).csv(path)
