"""Measures, fusion and grouping as functions for SQL: ``register(spark)`` and then plain queries.

gauss_o, gauss_oh, gauss_b, ... (p, q) are scalar functions over structs (n, mean, cov) for any D; fuse_clusters(n, mean, cov)
is an aggregate; cliques_of(TABLE edges) is a table function. The aggregate and the table function hold one group in a
worker: they are for groups of clusters, which are few, and not for rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from . import packed as P
from .deploy import ship


def _rows(x) -> list[np.ndarray]:
    return [np.asarray(v, float) for v in x]


def measure_udf(measure: str):
    """Scalar function (p, q) of one measure; null where it isn't defined or a side is null."""

    def run(p: pd.DataFrame, q: pd.DataFrame) -> pd.Series:
        out = np.full(len(p), np.nan)
        dims = np.array([len(m) if m is not None and n is not None else 0 for m, n in zip(p["mean"], q["mean"])])
        for d in set(dims.tolist()) - {0}:
            at = np.flatnonzero(dims == d)
            side = lambda x: (x["n"].to_numpy()[at].astype(float), np.array(_rows(x["mean"].iloc[at])), P.dense(np.array(_rows(x["cov"].iloc[at])), d))
            out[at] = K.pair_measures(*side(p), *side(q), (measure,))[measure]
        return pd.Series(out).astype(object).where(np.isfinite(out) | np.isinf(out), None)

    return F.pandas_udf(run, "double")


def _fused(n: pd.Series, mean: pd.Series, cov: pd.Series) -> list[float]:
    fit = n.notna() & mean.notna() & cov.notna() & (n > 0)
    if not fit.any():
        return []
    n_, m, s = n[fit].to_numpy().astype(float), np.array(_rows(mean[fit])), np.array(_rows(cov[fit]))
    total = n_.sum()
    centre = n_ @ m / total
    d = m - centre
    scatter = (n_ - 1) @ s + P.packed((d * n_[:, None]).T @ d)
    return [float(total), *centre.tolist(), *(scatter / max(total - 1, 1)).tolist()]


def fuse_udaf():
    """Aggregate (n, mean, cov) to one array: n, the mean and the packed covariance, one after another; empty without clusters."""

    def run(n: pd.Series, mean: pd.Series, cov: pd.Series) -> list:
        return _fused(n, mean, cov)

    return F.pandas_udf(run, "array<double>")


class CliquesOf:
    """Table function over edges (left_id, right_id, weight) of one partition: group_id, cluster_id of its disjoint cliques."""

    def __init__(self):
        self.weight = {}

    def eval(self, row):
        a, b = row["left_id"], row["right_id"]
        self.weight[(min(a, b), max(a, b))] = row["weight"]

    def terminate(self):
        from clusterfuse.operators.cliques import partition

        for group, _ in partition(sorted({v for e in self.weight for v in e}), self.weight):
            for v in group:
                yield min(group), v


def register(spark: SparkSession) -> None:
    """Make all functions known to ``spark.sql``."""
    ship(spark)
    for m in K.MEASURES:
        spark.udf.register(f"gauss_{m}", measure_udf(m))
    spark.udf.register("fuse_clusters", fuse_udaf())
    spark.udtf.register("cliques_of", F.udtf(CliquesOf, returnType="group_id bigint, cluster_id bigint"))
    # what the aggregate returns, as columns: n, mean, cov of dimension d
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fused_n(f ARRAY<DOUBLE>) RETURNS BIGINT RETURN CAST(f[0] AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fused_mean(f ARRAY<DOUBLE>, d INT) RETURNS ARRAY<DOUBLE> RETURN slice(f, 2, d)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fused_cov(f ARRAY<DOUBLE>, d INT) RETURNS ARRAY<DOUBLE> RETURN slice(f, d + 2, size(f) - d - 1)")
