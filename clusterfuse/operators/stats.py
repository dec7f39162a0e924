"""What is derived from a cluster once and never for a pair: diagonal, trace, log-determinants, largest eigenvalue, status."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import kernels as K
from ..functions import packed as P
from ..functions.deploy import ship


def lndet2(n: Column, a: Column, b: Column, c: Column) -> Column:
    """Log-determinant of a 2 x 2 covariance of n samples; null if it isn't positive definite."""
    det = a * c - b * b
    return F.when((n > 2) & (a > 0) & (det > 1e-12 * a * c), F.log(det))


def ln_hadamard(diag: Column) -> Column:
    """Sum of logs of the diagonal; null if an axis has no variance."""
    return F.when(F.forall(diag, lambda v: v > 0), F.aggregate(diag, F.lit(0.0), lambda s, v: s + F.log(v)))


def with_diagonal(clusters: DataFrame) -> DataFrame:
    """diag, trace and ln_hadamard, for any D, in the JVM."""
    x = clusters.withColumn("diag", P.diagonal(F.col("cov"), F.col("dim")))
    return x.withColumn("trace", F.aggregate("diag", F.lit(0.0), lambda s, v: s + v)).withColumn("ln_hadamard", ln_hadamard(F.col("diag")))


def with_stats(clusters: DataFrame, ridge: float | None = None) -> DataFrame:
    """with_diagonal, and lndet, lam_max, rank and status by batched factorizations; ``ridge`` is added to the diagonal first."""
    ship(clusters.sparkSession)
    base = with_diagonal(clusters)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            dims, n = b.column("dim").to_numpy(), b.column("n").to_numpy()
            out = {k: np.full(len(dims), np.nan) for k in ("lndet", "lam_max")}
            rank = np.zeros(len(dims), np.int32)
            covs = b.column("cov").to_pylist()
            for d in np.unique(dims):
                at = np.flatnonzero(dims == d)
                s = P.dense(np.array([covs[i] for i in at], float), int(d))
                if ridge:
                    s = s + ridge * np.eye(int(d))
                finite = np.isfinite(s).all((1, 2))
                lam = np.linalg.eigvalsh(np.where(finite[:, None, None], s, 0))
                out["lam_max"][at] = lam[:, -1]
                rank[at] = (lam > 1e-10 * np.maximum(lam[:, -1:], 1e-300)).sum(1)
                out["lndet"][at] = K.lndet(s) if ridge else K.cluster_lndet(n[at], s)
            status = ["NONFINITE" if not np.isfinite(lm) else "TOO_FEW" if k < 2 else "SINGULAR" if np.isnan(l) else "OK" for l, lm, k in zip(out["lndet"], out["lam_max"], n)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out["lndet"], from_pandas=True), pa.array(out["lam_max"]), pa.array(rank), pa.array(status)], names=[*b.schema.names, "lndet", "lam_max", "rank", "status"])

    schema = T.StructType([*base.schema.fields, T.StructField("lndet", T.DoubleType()), T.StructField("lam_max", T.DoubleType()), T.StructField("rank", T.IntegerType()), T.StructField("status", T.StringType())])
    return base.mapInArrow(run, schema)


def flat2(clusters: DataFrame) -> DataFrame:
    """D = 2 clusters as scalar columns: m1, m2, a, b, c, and lndet, ln_hadamard, trace, volume."""
    at = lambda c, k: F.element_at(c, k)
    x = clusters.select("model_id", "cluster_id", "n", at("mean", 1).alias("m1"), at("mean", 2).alias("m2"), at("cov", 1).alias("a"), at("cov", 2).alias("b"), at("cov", 3).alias("c"))
    x = x.withColumn("lndet", lndet2(F.col("n"), F.col("a"), F.col("b"), F.col("c")))
    return x.withColumn("ln_hadamard", F.when((F.col("a") > 0) & (F.col("c") > 0), F.log("a") + F.log("c"))).withColumn("trace", F.col("a") + F.col("c")).withColumn("volume", F.exp("lndet"))


def ellipse(clusters: DataFrame, k: float = 2.0) -> DataFrame:
    """Centre, half axes and angle of the k-sigma ellipse of D = 2 clusters."""
    x = flat2(clusters)
    half, root = (F.col("a") + F.col("c")) / 2, F.sqrt(F.pow((F.col("a") - F.col("c")) / 2, F.lit(2)) + F.col("b") * F.col("b"))
    axis = lambda v: k * F.sqrt(F.greatest(v, F.lit(0.0)))
    return x.select("cluster_id", F.col("m1").alias("cx"), F.col("m2").alias("cy"), axis(half + root).alias("semi_major"), axis(half - root).alias("semi_minor"), (0.5 * F.atan2(2 * F.col("b"), F.col("a") - F.col("c"))).alias("angle"))


#: Clusters that one native assignment holds, and bytes of one block of clusters that is sent to the workers.
NATIVE_CLUSTERS, BLOCK_BYTES = 1_000, 64 << 20


def assign2(rows: DataFrame, x1: str, x2: str, clusters: DataFrame) -> DataFrame:
    """``rows`` with ``assigned``, the D = 2 cluster of the highest Gaussian density (ties: the smaller id; null without a usable cluster).

    Up to NATIVE_CLUSTERS clusters it is one JVM expression; above, ``assign`` takes over."""
    if clusters.limit(NATIVE_CLUSTERS + 1).count() > NATIVE_CLUSTERS:
        return assign(rows, [x1, x2], clusters, 2)
    k = flat2(clusters).filter("lndet is not null")
    each = k.agg(F.array_sort(F.collect_list(F.struct("cluster_id", "m1", "m2", "a", "b", "c", "lndet"))).alias("ks"))
    of = lambda s: F.struct(((s["c"] * (F.col(x1) - s["m1"]) * (F.col(x1) - s["m1"]) - 2 * s["b"] * (F.col(x1) - s["m1"]) * (F.col(x2) - s["m2"]) + s["a"] * (F.col(x2) - s["m2"]) * (F.col(x2) - s["m2"])) / (s["a"] * s["c"] - s["b"] * s["b"]) + s["lndet"]).alias("cost"), s["cluster_id"].alias("cluster_id"))
    return rows.crossJoin(F.broadcast(each)).withColumn("assigned", F.array_min(F.transform("ks", of))["cluster_id"]).drop("ks")


def assign(rows: DataFrame, features: list[str], clusters: DataFrame, dim: int, blocks: int | None = None) -> DataFrame:
    """``rows`` with ``assigned``, the cluster of the highest Gaussian density in any D; works on streams too.

    Clusters without a volume take no part, rows with missing or non-finite features get null, ties the smaller id. The
    clusters go to the workers in blocks of bounded bytes, one pass of a chain of narrow maps for each, so any number of
    them is compared exactly and rows are never shuffled."""
    spark = rows.sparkSession
    ship(spark)
    known = clusters.filter(F.col("dim") == dim).select("cluster_id", "n", "mean", "cov")
    k = blocks or max(1, -(-known.count() * 8 * dim * (dim + 3) // BLOCK_BYTES))
    schema = T.StructType([*rows.schema.fields, T.StructField("assigned", T.LongType()), T.StructField("_cost", T.DoubleType())])
    out = rows.withColumn("assigned", F.lit(None).cast("long")).withColumn("_cost", F.lit(None).cast("double"))
    for b in range(k):
        block = sorted(known.filter(F.pmod(F.xxhash64("cluster_id"), F.lit(k)) == b).collect())
        ids = np.array([r["cluster_id"] for r in block], np.int64)
        ln, roots, means = np.zeros(0), np.zeros((0, dim, dim)), np.zeros((0, dim))
        if block:
            s = P.dense(np.array([r["cov"] for r in block], float), dim)
            ln = K.cluster_lndet(np.array([r["n"] for r in block], float), s)
            fit = np.isfinite(ln)
            ids, ln, means = ids[fit], ln[fit], np.array([r["mean"] for r in block], float)[fit]
            # whitening maps: the squared length of what they make of a gap is its Mahalanobis distance
            roots = np.linalg.inv(np.linalg.cholesky(s[fit]))
        shared = spark.sparkContext.broadcast((ids, ln, roots, means))
        out = out.mapInArrow(_nearest(shared, features, dim), schema)
    return out.drop("_cost")


def _nearest(shared, features: list[str], dim: int):
    def run(batches):
        import pyarrow as pa

        ids, ln, roots, means = shared.value
        for b in batches:
            x = np.stack([b.column(f).to_numpy(zero_copy_only=False).astype(float) for f in features], axis=1).reshape(-1, dim)
            fine = np.isfinite(x).all(1)
            best = b.column("assigned").to_pylist()
            cost = b.column("_cost").to_numpy(zero_copy_only=False).astype(float)
            for at in range(0, len(x) if len(ids) else 0, 1024):
                here = np.flatnonzero(fine[at : at + 1024]) + at
                each = np.empty((len(here), len(ids)))
                for j in range(len(ids)):
                    each[:, j] = (((x[here] - means[j]) @ roots[j].T) ** 2).sum(1) + ln[j]
                first = each.argmin(1) if len(here) else np.zeros(0, int)
                for row, j, c in zip(here, first, each[np.arange(len(here)), first]):
                    if not cost[row] < c and (cost[row] != c or int(ids[j]) < best[row]):
                        best[row], cost[row] = int(ids[j]), c
            yield pa.RecordBatch.from_arrays([*b.columns[:-2], pa.array(best, pa.int64()), pa.array(cost, pa.float64(), from_pandas=True)], names=b.schema.names)

    return run
