"""Cluster sets and pair scenarios: predicates on lineitem, discs, and generated clusters of any D."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.summarize import CLUSTER, standardize, summarize_columns
from . import tables

NAMES = ["a", "b", "c_tight", "c_loose", "d_axis", "d_diag"]
EXPECT_OVERLAP = {"a": True, "b": False, "c_tight": True, "c_loose": True, "d_axis": False, "d_diag": False}


def lineitem_z(spark: SparkSession, sf_dir: str, dim: int = 2, extra: tuple[str, ...] = ()) -> DataFrame:
    """lineitem with z-scores z1.. of quantity, price, discount, tax; only the columns asked for are read."""
    features = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"][:dim]
    wanted = list(dict.fromkeys([*features, "l_quantity", "l_extendedprice", *extra]))
    return standardize(tables.read_table(spark, sf_dir, "lineitem", wanted), features)


def sides() -> list[tuple[str, int, Column]]:
    """(scenario, side, predicate) over lineitem_z."""
    q, p, u, v = F.col("l_quantity"), F.col("l_extendedprice"), (F.col("z1") + F.col("z2")) / F.sqrt(F.lit(2.0)), (F.col("z1") - F.col("z2")) / F.sqrt(F.lit(2.0))
    tight, loose = q.between(23, 28) & p.between(47000, 59000), q.between(21, 30) & p.between(40000, 66000)
    square, near = (F.abs(u) < 1.5) & (F.abs(v) < 1.5), lambda x: F.abs(x) < 0.2
    flag = lambda r: (F.col("l_returnflag") == r) & (F.col("l_linestatus") == "F")
    band_q, band_p = q.between(24, 27), p.between(49000, 57000)
    return [
        ("a", 0, flag("A")), ("a", 1, flag("R")),
        ("b", 0, (q <= 10) & (p <= 25000)), ("b", 1, (q >= 41) & (p >= 80000)),
        ("c_tight", 0, ~tight), ("c_tight", 1, tight),
        ("c_loose", 0, ~loose), ("c_loose", 1, loose),
        ("d_axis", 0, band_q & ~band_p), ("d_axis", 1, band_p & ~band_q),
        ("d_diag", 0, square & near(u) & ~near(v)), ("d_diag", 1, square & near(v) & ~near(u)),
    ]


def scenario_clusters(spark: SparkSession, sf_dir: str, dim: int = 2) -> DataFrame:
    """Both sides of all scenarios in one scan: model_id is the scenario, cluster_id the side."""
    li = lineitem_z(spark, sf_dir, dim, ("l_returnflag", "l_linestatus"))
    tags = F.explode(F.array_compact(F.array(*[F.when(on, F.struct(F.lit(s).alias("scenario"), F.lit(k).alias("side"))) for s, k, on in sides()])))
    tagged = li.withColumn("tag", tags)
    return summarize_columns(tagged, F.col("tag.side"), [f"z{i + 1}" for i in range(dim)], F.col("tag.scenario"))


def discs(li: DataFrame) -> DataFrame:
    """Clusters of the rows in 24 discs of the (z1, z2) plane; a row may lie in several (a range join with a constant table)."""
    k = li.sparkSession.range(24).select(
        F.col("id").alias("disc"),
        (F.pmod(37 * F.col("id"), F.lit(24)) / 23 * 2.8 - 1.4).alias("x"),
        (F.pmod(17 * F.col("id") + 5, F.lit(24)) / 23 * 2.8 - 1.4).alias("y"),
        (0.35 + 0.05 * F.pmod("id", F.lit(5))).alias("r"),
    )
    inside = li.select("z1", "z2").join(F.broadcast(k), (F.col("z1") - F.col("x")) * (F.col("z1") - F.col("x")) + (F.col("z2") - F.col("y")) * (F.col("z2") - F.col("y")) <= F.col("r") * F.col("r"))
    return summarize_columns(inside, F.col("disc"), ["z1", "z2"])


def generate(dim: int, kind: str, seed: int = 0) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """Two exact clusters (n, mean, covariance) of scenario a (overlap), b (apart), c (small in large) or d (orthogonal).

    Centres lie 0.28 (a) or 3 (b) deviations apart on each axis, so that distances grow with D; d swaps a variance of 1 with
    one of 0.05 between two directions of a common centre, turned by 0.3 radians in the plane and at random above."""
    rng = np.random.default_rng([seed, dim, ord(kind)])
    basis, _ = np.linalg.qr(rng.normal(size=(dim, dim)))
    lam = rng.uniform(0.5, 1.5, dim)
    turned = lambda x: (basis * x) @ basis.T
    mean, n = rng.normal(size=dim), 50 * dim
    step = basis @ (np.sqrt(lam) * rng.choice([-1.0, 1.0], dim))
    if kind == "a":
        return [(n, mean, turned(lam)), (n, mean + 0.28 * step, turned(lam * rng.uniform(0.95, 1.05, dim)))]
    if kind == "b":
        return [(n, mean, turned(lam)), (n, mean + 3 * step, turned(lam))]
    if kind == "c":
        return [(10 * n, mean, turned(lam * 100)), (n, mean + basis[:, 0], turned(lam))]
    if dim == 2:
        basis = np.array([[np.cos(0.3), -np.sin(0.3)], [np.sin(0.3), np.cos(0.3)]])
    one, two = lam.copy(), lam.copy()
    one[0] = two[1] = 1.0
    one[1] = two[0] = 0.05
    return [(n, mean, turned(one)), (n, mean, turned(two))]


def generated_clusters(spark: SparkSession, dim: int, seed: int = 0) -> DataFrame:
    """All four generated scenarios as clusters."""
    from ..functions.packed import packed

    rows = [(kind, side, dim, int(n), [float(x) for x in m], [float(x) for x in packed(s)]) for kind in "abcd" for side, (n, m, s) in enumerate(generate(dim, kind, seed))]
    return spark.createDataFrame(rows, CLUSTER)
