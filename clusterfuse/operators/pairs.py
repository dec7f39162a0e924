"""Unordered pairs of clusters, whole or narrowed by candidate criteria."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import LN2
from .stats import flat2

#: One side of a pair join may be broadcast up to so many clusters and so many bytes of their arrays; beyond, pairs are made by blocks.
BROADCAST_CLUSTERS, BROADCAST_BYTES = 20_000, 128 << 20
#: Pairs that a task makes, about, while there are idle cores.
TASK_PAIRS = 20_000


def extent(clusters: DataFrame, columns: list[str]) -> tuple[int, int]:
    """Number of clusters and bytes of their array columns, counted up to just beyond what may be broadcast."""
    arrays = [c for c, kind in clusters.select(*columns).dtypes if kind.startswith("array")]
    bytes_ = F.lit(16)
    for c in arrays:
        bytes_ = bytes_ + 8 * F.greatest(F.size(c), F.lit(0))
    n, size = clusters.limit(BROADCAST_CLUSTERS + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(bytes_), F.lit(0))).first()
    return n, size


def may_broadcast(clusters: DataFrame, columns: list[str]) -> bool:
    n, size = extent(clusters, columns)
    return n <= BROADCAST_CLUSTERS and size <= BROADCAST_BYTES


def all_pairs(clusters: DataFrame, columns: list[str] | None = None, blocks: int | None = None) -> DataFrame:
    """Pairs (left_id < right_id) of one model with structs p and q of ``columns``.

    Small sets are broadcast after their number and bytes were checked, and the other side is dealt over the cores; larger
    ones are dealt into blocks, and two blocks meet in one task by an equi-join, so that each cluster is copied once for
    each block."""
    columns = columns or [c for c in clusters.columns if c not in ("model_id", "cluster_id")]
    one = clusters.select("model_id", F.col("cluster_id").alias("left_id"), F.struct(*columns).alias("p"))
    two = clusters.select("model_id", F.col("cluster_id").alias("right_id"), F.struct(*columns).alias("q"))
    n, size = extent(clusters, columns)
    if blocks is None and n <= BROADCAST_CLUSTERS and size <= BROADCAST_BYTES:
        # a stored table of clusters is one file: without dealing, one task would make all pairs
        tasks = min(4 * clusters.sparkSession.sparkContext.defaultParallelism, n * n // 2 // TASK_PAIRS + 1)
        one = one.repartition(tasks, "left_id") if tasks > 1 else one
        return one.join(F.broadcast(two), (one.model_id == two.model_id) & (F.col("left_id") < F.col("right_id"))).select(one.model_id, "left_id", "right_id", "p", "q")
    if blocks is None:
        # blocks of a few thousand clusters, or of as many as the bytes allow
        each = max(1, min(4096, BROADCAST_BYTES // 8 // max(1, size // max(n, 1))))
        blocks = max(2, -(-clusters.count() // each))
    k = blocks
    every = F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    left = one.withColumn("i", F.pmod(F.xxhash64("left_id"), F.lit(k)).cast("int")).withColumn("j", every)
    right = two.withColumn("j", F.pmod(F.xxhash64("right_id"), F.lit(k)).cast("int")).withColumn("i", every)
    return left.join(right, ["model_id", "i", "j"]).filter("left_id < right_id").select("model_id", "left_id", "right_id", "p", "q")


def fresh_pairs(clusters: DataFrame, columns: list[str]) -> DataFrame:
    """Pairs of which at least one side is ``fresh`` (a boolean column), in the form of all_pairs."""
    new = clusters.filter("fresh").select("model_id", F.col("cluster_id").alias("new_id"), F.struct(*columns).alias("x"))
    old = clusters.select("model_id", F.col("cluster_id").alias("old_id"), "fresh", F.struct(*columns).alias("y"))
    new = F.broadcast(new) if may_broadcast(clusters.filter("fresh"), columns) else new
    # two fresh sides meet once
    met = old.join(new, "model_id").filter((F.col("old_id") != F.col("new_id")) & (~F.col("fresh") | (F.col("old_id") < F.col("new_id"))))
    first = F.col("new_id") < F.col("old_id")
    return met.select("model_id", F.least("new_id", "old_id").alias("left_id"), F.greatest("new_id", "old_id").alias("right_id"), F.when(first, F.col("x")).otherwise(F.col("y")).alias("p"), F.when(first, F.col("y")).otherwise(F.col("x")).alias("q"))


def box_candidates(clusters: DataFrame, k: float = 2.0, cell: float = 1.0) -> DataFrame:
    """Pairs of D = 2 clusters whose k-sigma boxes overlap on both axes: a range join by grid cells. A heuristic: pairs beyond it are not measured."""
    x = flat2(clusters)
    box = x.select("model_id", "cluster_id", *[(F.col(m) + s * k * F.sqrt(v)).alias(f"{m}_{n}") for m, v in (("m1", "a"), ("m2", "c")) for s, n in ((-1, "lo"), (1, "hi"))])
    spread = lambda m: F.explode(F.sequence(F.floor(F.col(f"{m}_lo") / cell), F.floor(F.col(f"{m}_hi") / cell)))
    cells = box.withColumn("g1", spread("m1")).withColumn("g2", spread("m2"))
    p, q = cells.alias("p"), cells.alias("q")
    on = (F.col("p.model_id") == F.col("q.model_id")) & (F.col("p.g1") == F.col("q.g1")) & (F.col("p.g2") == F.col("q.g2")) & (F.col("p.cluster_id") < F.col("q.cluster_id"))
    for m in ("m1", "m2"):
        on = on & (F.col(f"p.{m}_lo") <= F.col(f"q.{m}_hi")) & (F.col(f"q.{m}_lo") <= F.col(f"p.{m}_hi"))
    # a pair is reported by the first cell of its common box only, so nothing is shuffled to tell copies apart
    for g, m in (("g1", "m1"), ("g2", "m2")):
        on = on & (F.col(f"p.{g}") == F.floor(F.greatest(F.col(f"p.{m}_lo"), F.col(f"q.{m}_lo")) / cell))
    return p.join(q, on).select(F.col("p.model_id").alias("model_id"), F.col("p.cluster_id").alias("left_id"), F.col("q.cluster_id").alias("right_id"))


def lower_bound(pairs: DataFrame, dim: int) -> DataFrame:
    """``pairs`` (p, q with n, mean, lndet, trace) with ``bound``, which O never falls below; null where a side has no volume."""
    p, q = F.col("p"), F.col("q")
    n1, n2 = p["n"].cast("double"), q["n"].cast("double")
    n = n1 + n2
    w1, w2, c = (n1 - 1) / (n - 1), (n2 - 1) / (n - 1), n1 / n * n2 / (n - 1)
    gap2 = F.aggregate(F.zip_with(p["mean"], q["mean"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    sum_of: Column = dim * lse(F.log(w1) + p["lndet"] / dim, F.log(w2) + q["lndet"] / dim)
    bound = F.lit(LN2) + sum_of + F.log1p(c * gap2 / (w1 * p["trace"] + w2 * q["trace"])) - lse(p["lndet"], q["lndet"])
    # without a volume nothing is known, and such a pair has to be measured
    return pairs.withColumn("bound", F.when(p["lndet"].isNotNull() & q["lndet"].isNotNull(), bound))


def lse(a: Column, b: Column) -> Column:
    """ln(e^a + e^b); a missing side counts as zero volume."""
    return F.when(a.isNull(), b).when(b.isNull(), a).otherwise(F.greatest(a, b) + F.log1p(F.exp(-F.abs(a - b))))
