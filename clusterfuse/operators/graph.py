"""The overlap graph: edges below a threshold, its shape, its components."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import discard, store

#: Read off published values of o for D = 2 and D = 100, which one cut between 1.46 and 1.52 separates.
THRESHOLD = 1.5


def edges(measured: DataFrame, measure: str = "o", threshold: float = THRESHOLD) -> DataFrame:
    """Pairs whose measure is strictly below the threshold: left_id, right_id, weight."""
    return measured.filter(F.col(measure) < threshold).select("left_id", "right_id", F.col(measure).alias("weight"))


def adjacency(found: DataFrame) -> DataFrame:
    """Both directions of the edges."""
    return found.select("left_id", "right_id", "weight").unionByName(found.select(F.col("right_id").alias("left_id"), F.col("left_id").alias("right_id"), "weight"))


def adjacency_matrix(found: DataFrame, nodes: DataFrame) -> DataFrame:
    """A row of 0 and 1 for each node over all nodes in id order; for the few nodes of one component."""
    ids = nodes.select("cluster_id").agg(F.array_sort(F.collect_set("cluster_id")).alias("ids"))
    near = adjacency(found).groupBy("left_id").agg(F.collect_set("right_id").alias("near"))
    rows = nodes.select("cluster_id").join(near, F.col("cluster_id") == F.col("left_id"), "left").crossJoin(F.broadcast(ids))
    return rows.select("cluster_id", F.transform("ids", lambda i: F.coalesce(F.array_contains("near", i), F.lit(False)).cast("int")).alias("row"))


def degrees(found: DataFrame, nodes: DataFrame) -> DataFrame:
    deg = adjacency(found).groupBy("left_id").agg(F.count(F.lit(1)).alias("degree"))
    return nodes.select("cluster_id").join(deg, F.col("cluster_id") == F.col("left_id"), "left").select("cluster_id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def touched(nodes: DataFrame, found: DataFrame) -> DataFrame:
    return nodes.join(adjacency(found), F.col("cluster_id") == F.col("left_id"), "left_semi")


def isolated(nodes: DataFrame, found: DataFrame) -> DataFrame:
    return nodes.join(adjacency(found), F.col("cluster_id") == F.col("left_id"), "left_anti")


def components(found: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """cluster_id and component_id, the smallest id that it reaches; nodes without edges are components of their own.

    Smallest labels spread along edges and jump to the label of their label, so rounds grow with the log of a path; each
    round is a table in the shared folder and the driver sees only whether something moved."""
    both = store(adjacency(found).select("left_id", "right_id").distinct(), "edges")
    labels = store(both.groupBy(F.col("left_id").alias("cluster_id")).agg(F.least(F.min("right_id"), F.col("cluster_id")).alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("cluster_id").alias("right_id"), "label"), "right_id").groupBy(F.col("left_id").alias("cluster_id")).agg(F.min("label").alias("near"))
        low = labels.join(near, "cluster_id").select("cluster_id", F.col("label").alias("old"), F.least("label", "near").alias("low"))
        jump = low.select(F.col("cluster_id").alias("low"), F.col("low").alias("lower"))
        before, labels = labels, store(low.join(jump, "low", "left").select("cluster_id", "old", F.least("low", F.coalesce("lower", "low")).alias("label")), "labels")
        discard(before)
        if labels.filter("label <> old").isEmpty():
            break
    discard(both)
    out = labels.select("cluster_id", F.col("label").alias("component_id"))
    if nodes is None:
        return out
    return nodes.select("cluster_id").join(out, "cluster_id", "left").select("cluster_id", F.coalesce("component_id", "cluster_id").alias("component_id"))
