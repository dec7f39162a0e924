"""Pairs by tiles against the expressions that measure one pair in a row."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from clusterfuse.operators import measures, pairs, tiles
from clusterfuse.operators.summarize import CLUSTER


@pytest.fixture(scope="module")
def odd(spark):
    """Two models; among their clusters some without a volume, of one sample, equal to another, and of billions of samples."""
    rng = np.random.default_rng(11)
    rows = []
    for model, n in (("x", 40), ("y", 7)):
        for k in range(n):
            a, c, rho = *rng.uniform(0.1, 3, 2), rng.uniform(-0.9, 0.9)
            rows.append((model, 3 * k - 20, 2, int(rng.integers(3, 90)), [float(v) for v in rng.normal(size=2)], [float(a), float(rho * np.sqrt(a * c)), float(c)]))
        rows += [(model, 1000, 2, 9, [0.0, 1.0], [1.0, 1.0, 1.0]), (model, 1001, 2, 9, [2.0, 1.0], [4.0, 2.0, 1.0]), (model, 1002, 2, 1, [0.5, 0.5], [0.0, 0.0, 0.0]), (model, 1003, 2, 1, [0.5, 0.5], [0.0, 0.0, 0.0]), (model, 1004, 2, 3 * 10**9, [0.1, 0.2], [1.0, 0.2, 2.0])]
        rows.append((model, 1005, *rows[0][2:]))
    return spark.createDataFrame(rows, CLUSTER)


@pytest.fixture
def small_blocks(monkeypatch):
    monkeypatch.setattr(tiles, "SMALL_BLOCK", 8)
    monkeypatch.setattr(tiles, "STEP", 20)


def expected(odd, columns):
    return measures.flat_pairs2(pairs.all_pairs(odd, ["n", "mean", "cov"])).select("model_id", "left_id", "right_id", *columns)


def place(x):
    return x.toPandas().sort_values(["model_id", "left_id", "right_id"]).reset_index(drop=True)


def test_largest_gap_covers_every_pair(odd, small_blocks):
    js, b = measures.measure2("js", True), measures.measure2("b")
    want = expected(odd, [js.alias("js"), b.alias("b")]).agg(F.count(F.lit(1)), F.max(F.abs(F.col("js") - F.col("b"))), F.max("b")).first()
    got = tiles.largest_gap(odd, ["js_literal", "b"], lambda v: abs(v["js_literal"] - v["b"])).first()
    assert got["n_pairs"] == want[0] == 46 * 45 // 2 + 13 * 12 // 2 and got["gap"] < 1e-9 and want[1] < 1e-9
    assert tiles.largest_gap(odd, ["b"], lambda v: v["b"]).first()["gap"] == pytest.approx(want[2], rel=1e-12)
    none = tiles.largest_gap(odd.limit(0), ["b"], lambda v: v["b"]).first()
    assert none["n_pairs"] == 0 and none["gap"] is None


def test_measured_tiles_are_the_measures_of_all_pairs(odd, small_blocks):
    want, got = place(expected(odd, [measures.measure2(m).alias(m) for m in measures.MEASURES])), place(tiles.measured(odd))
    assert len(got) == len(want) and (got[["model_id", "left_id", "right_id"]] == want[["model_id", "left_id", "right_id"]]).all(None)
    for m in measures.MEASURES:
        assert (got[m].isna() == want[m].isna()).all() and want[m].isna().any() == (m != "w"), m
        assert np.allclose(got[m].fillna(0), want[m].fillna(0), rtol=1e-9, atol=1e-9), m


def test_nearest_by_tiles_keep_missing_values_last(odd, small_blocks):
    one = expected(odd, [measures.measure2("o").alias("o")])
    both = one.union(one.select("model_id", "right_id", "left_id", "o")).toPandas()
    both["o"] = both["o"].fillna(np.inf)
    want = both.sort_values(["model_id", "left_id", "o", "right_id"]).groupby(["model_id", "left_id"]).head(3)
    got = tiles.nearest(odd, "o", 3).toPandas().sort_values(["model_id", "left_id", "place"])
    assert list(map(tuple, got[["model_id", "left_id"]].values)) == list(map(tuple, want[["model_id", "left_id"]].values))
    assert np.allclose(got["value"].fillna(1e9), want["o"].replace(np.inf, 1e9), rtol=1e-9, atol=1e-9)
    # more places than clusters: everyone is placed, those without a value at the end
    every = tiles.nearest(odd, "o", 100).filter("model_id = 'y'").toPandas()
    assert len(every) == 13 * 12 and every[every["value"].isna()]["place"].min() > 8


def test_volume_ratio_and_overlap_by_tiles(odd, small_blocks):
    """Both sides of the identity, also where one side or both have no volume."""
    o = expected(odd, [measures.measure2("o").alias("o"), measures.measure2("vr").alias("vr")]).agg(F.max("o"), F.max("vr"), F.max(-F.col("o"))).first()
    for k, (which, value) in enumerate([("o", lambda v: v["o"]), ("vr", lambda v: v["vr"]), ("o", lambda v: -v["o"])]):
        assert tiles.largest_gap(odd, [which], value).first()["gap"] == pytest.approx(o[k], rel=1e-12)


def test_least_pairs_by_tiles(odd, small_blocks):
    want = expected(odd.filter("model_id = 'x'"), [measures.measure2("o").alias("o")]).toPandas()
    want["o"] = want["o"].fillna(np.inf)
    want = want.sort_values(["o", "left_id", "right_id"])
    for k in (1, 10, 2000):
        got = tiles.least(odd.filter("model_id = 'x'"), "o", k).toPandas()
        assert len(got) == min(k, len(want)) and np.allclose(got["value"].fillna(1e9), want["o"].replace(np.inf, 1e9)[:k], rtol=1e-9, atol=1e-9)
    # the pairs without a value come last, in the order of their ids
    assert np.isnan(got["value"].values[-1]) and list(got[got["value"].isna()]["left_id"]) == sorted(got[got["value"].isna()]["left_id"])
