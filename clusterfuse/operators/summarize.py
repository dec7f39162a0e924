"""Clusters (n, mean, packed covariance) from rows, in one scan: raw rows are never shuffled, only partial moments are.

All summaries use the same rows: those with a cluster_id whose features are all there and finite."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import packed as P
from ..functions.deploy import ship

CLUSTER = "model_id string, cluster_id bigint, dim int, n bigint, mean array<double>, cov array<double>"


def usable(features: list[str]) -> Column:
    """Rows whose features are all present and finite."""
    out = F.lit(True)
    for f in features:
        x = F.col(f).cast("double")
        out = out & x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))
    return out


def clean(df: DataFrame, features: list[str]) -> DataFrame:
    return df.filter(usable(features))


def clean_counts(df: DataFrame, keys: list[str], features: list[str]) -> DataFrame:
    """Used and rejected rows of each key."""
    ok = usable(features)
    return df.groupBy(*keys).agg(F.count_if(ok).alias("n_used"), F.count_if(~ok).alias("n_rejected"))


def standardize(df: DataFrame, features: list[str], names: list[str] | None = None) -> DataFrame:
    """``df`` with z-scores of ``features``; the global means and deviations are one row."""
    names = names or [f"z{i + 1}" for i in range(len(features))]
    stats = df.agg(*[F.avg(f).alias(f"avg_{i}") for i, f in enumerate(features)], *[F.stddev_samp(f).alias(f"sd_{i}") for i, f in enumerate(features)])
    both = df.crossJoin(F.broadcast(stats))
    return both.select(*df.columns, *[((F.col(f) - F.col(f"avg_{i}")) / F.col(f"sd_{i}")).alias(z) for i, (f, z) in enumerate(zip(features, names))])


def summarize_columns(df: DataFrame, cluster_id: Column, features: list[str], model_id: Column | str = "all") -> DataFrame:
    """Clusters by an id expression from scalar columns: partial and final hash aggregates in the JVM; for up to about 12 features."""
    model = F.lit(model_id) if isinstance(model_id, str) else model_id
    x = df.select(model.alias("model_id"), cluster_id.cast("long").alias("cluster_id"), *[F.col(f).cast("double").alias(f"x{i}") for i, f in enumerate(features)])
    x = clean(x.filter("cluster_id is not null"), [f"x{i}" for i in range(len(features))])
    d = len(features)
    cov = [F.var_samp(f"x{i}") if i == j else F.covar_samp(f"x{i}", f"x{j}") for i, j in P.slots(d)]
    out = x.groupBy("model_id", "cluster_id").agg(F.count(F.lit(1)).alias("n"), *[F.avg(f"x{i}").alias(f"m{i}") for i in range(d)], *[c.alias(f"c{k}") for k, c in enumerate(cov)])
    # one sample has no covariance: zeros by convention, which its weight n - 1 cancels
    return out.select("model_id", "cluster_id", F.lit(d).alias("dim"), "n", F.array(*[f"m{i}" for i in range(d)]).alias("mean"), F.array(*[F.coalesce(F.col(f"c{k}"), F.lit(0.0)) for k in range(len(cov))]).alias("cov"))


def summarize_vectors_sql(df: DataFrame, cluster_id: Column, vec: str, dim: int, model_id: str = "all") -> DataFrame:
    """Clusters from the first ``dim`` entries of a vector column without Python: pairs of slots as rows; for up to about 16 axes."""
    x = df.select(cluster_id.cast("long").alias("cluster_id"), F.transform(F.slice(vec, 1, dim), lambda v: v.cast("double")).alias("v"))
    x = x.filter(F.col("cluster_id").isNotNull() & (F.size("v") == dim) & F.forall("v", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf"))))
    one = x.select("cluster_id", "v", F.posexplode("v").alias("i", "a")).select("cluster_id", "i", "a", F.posexplode("v").alias("j", "b")).filter("i <= j")
    each = one.groupBy("cluster_id", "i", "j").agg(F.count(F.lit(1)).alias("n"), F.avg("a").alias("m"), F.covar_samp("a", "b").alias("c"))
    slot = F.struct("i", "j", "m", F.coalesce("c", F.lit(0.0)).alias("c"))
    got = each.groupBy("cluster_id").agg(F.max("n").alias("n"), F.array_sort(F.collect_list(slot)).alias("s"))
    return got.select(F.lit(model_id).alias("model_id"), "cluster_id", F.lit(dim).alias("dim"), "n", F.transform(F.filter("s", lambda s: s["i"] == s["j"]), lambda s: s["m"]).alias("mean"), F.transform("s", lambda s: s["c"]).alias("cov"))


#: Bytes of partial moments that a task holds before it sends them on, and parts that a hot key's partial moments are added up in first.
HELD_BYTES, PARTS = 128 << 20, 64


def vectors(column, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """The first ``dim`` entries of an Arrow list column as rows, and which of its entries they belong to; short and missing ones are left out."""
    import pyarrow.compute as pc

    offsets = column.offsets.to_numpy()
    values = column.values.to_numpy(zero_copy_only=False).astype(float)
    fit = np.flatnonzero(pc.fill_null(pc.is_valid(column), False).to_numpy(zero_copy_only=False) & (np.diff(offsets) >= dim))
    return values[offsets[:-1][fit][:, None] + np.arange(dim)], fit


def joined_moments(one: tuple | None, n: float, mean: np.ndarray, m2: np.ndarray) -> tuple:
    """Moments (n, mean, packed scatter) of two sets of rows together."""
    if one is None:
        return n, mean, m2
    total, d = one[0] + n, mean - one[1]
    return total, one[1] + d * (n / total), one[2] + m2 + P.packed(np.outer(d, d) * (one[0] * n / total))


def summarize_vectors(df: DataFrame, cluster_id: Column, vec: str, dim: int, model_id: str = "all") -> DataFrame:
    """Clusters of any D from a vector column: centred moments of each key, added up within a task and combined by the fusion identity.

    A task sends one row for each of its keys (or more, when its moments outgrow HELD_BYTES and are sent early). The rows of
    a hot key, one for each task, are combined in PARTS parts first, so that no task reads a key's rows of all tasks."""
    ship(df.sparkSession)
    schema = "cluster_id long, part int, n double, mean array<double>, m2 array<double>"

    def partial(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        part = (TaskContext.get().partitionId() if TaskContext.get() else 0) % PARTS
        held: dict[int, tuple] = {}
        most = max(1, HELD_BYTES // (4 * dim * (dim + 3)))

        def sent():
            keys = list(held)
            cols = [pa.array(keys, pa.int64()), pa.array([part] * len(keys), pa.int32()), pa.array([held[k][0] for k in keys], pa.float64()), *[pa.array([held[k][i] for k in keys], pa.list_(pa.float64())) for i in (1, 2)]]
            held.clear()
            return pa.RecordBatch.from_arrays(cols, names=["cluster_id", "part", "n", "mean", "m2"])

        for b in batches:
            x, at = vectors(b.column(1), dim)
            ids = b.column(0).to_numpy(zero_copy_only=False)[at]
            fine = np.isfinite(x).all(1)
            order = np.argsort(ids[fine], kind="stable")
            x, ids = x[fine][order], ids[fine][order]
            edge = np.flatnonzero(np.diff(ids, prepend=ids[0] - 1)) if len(ids) else np.zeros(0, int)
            for lo, hi in zip(edge, np.append(edge[1:], len(ids))):
                rows = x[lo:hi]
                mean = rows.mean(0)
                y = rows - mean
                held[int(ids[lo])] = joined_moments(held.get(int(ids[lo])), float(hi - lo), mean, P.packed(y.T @ y))
            if len(held) > most:
                yield sent()
        yield sent()

    def added(t):
        n = t["n"].to_numpy()
        means, m2 = (np.asarray(t[c].combine_chunks().flatten().to_numpy(zero_copy_only=False)).reshape(len(n), -1) for c in ("mean", "m2"))
        # rows come in the order of the shuffle; sums in a fixed order give the same digits in every run
        order = np.lexsort((means[:, 0], n))
        n, means, m2 = n[order], means[order], m2[order]
        total = n.sum()
        mean = n @ means / total
        d = means - mean
        return total, mean, m2.sum(0) + P.packed((d * n[:, None]).T @ d)

    def combine_part(t):
        import pyarrow as pa

        total, mean, m2 = added(t)
        return pa.table({"cluster_id": [t["cluster_id"][0].as_py()], "part": pa.array([0], pa.int32()), "n": [total], "mean": pa.array([mean]), "m2": pa.array([m2])})

    def combine(t):
        import pyarrow as pa

        total, mean, scatter = added(t)
        return pa.table({"model_id": [model_id], "cluster_id": [t["cluster_id"][0].as_py()], "dim": pa.array([dim], pa.int32()), "n": pa.array([int(total)], pa.int64()), "mean": pa.array([mean]), "cov": pa.array([scatter / max(total - 1, 1)])})

    parts = df.select(cluster_id.cast("long").alias("cluster_id"), vec).filter("cluster_id is not null").mapInArrow(partial, schema)
    return parts.groupBy("cluster_id", "part").applyInArrow(combine_part, schema).groupBy("cluster_id").applyInArrow(combine, CLUSTER)


def distinct_per_cluster(df: DataFrame, keys: list[str], col: str, approx: bool = False) -> DataFrame:
    count = F.approx_count_distinct if approx else F.count_distinct
    return df.groupBy(*keys).agg(count(col).alias("n_distinct"))
