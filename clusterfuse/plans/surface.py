"""SQL views over a set of clusters, and helpers that read plans."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..operators import cliques, fuse, graph, measures, pairs
from ..sources.tables import store


def create_views(clusters: DataFrame, dim: int, threshold: float = graph.THRESHOLD) -> None:
    """Temporary views clusters, pairs (all measures), edges, groups and fused, and the functions of ``sqlfuncs``.

    Each step is a table in the shared folder, so that queries over the views don't measure again."""
    sqlfuncs.register(clusters.sparkSession)
    k = store(clusters, "clusters")
    measured = store(measures.measure_pairs(pairs.all_pairs(k, ["n", "mean", "cov"]), dim), "pairs")
    found = store(graph.edges(measured, "o", threshold), "edges")
    groups = store(cliques.disjoint_groups(found, k), "groups")
    for name, df in (("clusters", k), ("pairs", measured), ("edges", found), ("groups", groups), ("fused", fuse.fuse_groups(k, groups))):
        df.createOrReplaceTempView(name)


def plan_of(df: DataFrame) -> str:
    """The physical plan as text."""
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    """Shuffles in the plan, broadcasts not among them."""
    return len(re.findall(r"(?<!Broadcast)(?<!Reused)Exchange ", plan_of(df)))


def runs_python(df: DataFrame) -> bool:
    return bool(re.search(r"Python|Pandas|InArrow|InPandas", plan_of(df)))


def columns_read(df: DataFrame) -> set[str]:
    """Columns that the scans read, nested types cut off."""
    return {c.split(":")[0] for found in re.findall(r"ReadSchema: struct<([^\n]*)>", plan_of(df)) for c in re.split(r",(?=\w+:)", found) if c}


def pushed_filters(df: DataFrame) -> list[str]:
    return [x for found in re.findall(r"PushedFilters: \[([^\n]*?)\], ReadSchema", plan_of(df)) for x in re.split(r", (?=\w+\()", found) if x]


def partition_filters(df: DataFrame) -> list[str]:
    return [x for x in re.findall(r"PartitionFilters: \[([^\n]*?)\], PushedFilters", plan_of(df)) if x]


def with_hint(df: DataFrame, hint: str) -> DataFrame:
    """``df`` with a join hint: broadcast, merge or shuffle_hash."""
    if hint not in ("broadcast", "merge", "shuffle_hash"):
        raise ValueError(hint)
    return df.hint(hint) if hint != "broadcast" else F.broadcast(df)
