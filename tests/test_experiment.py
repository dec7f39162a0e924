"""The queries of the comparison read their table: other tables give other rows."""

import numpy as np
import pytest
from conftest import SMALL
from pyspark.sql import functions as F

from clusterfuse.plans import catalog, experiment

OTHER = "/root/testdata/sf0.01"


def both(spark, name, *keys):
    one, two = ({tuple(r[k] for k in keys): r for r in catalog.queries()[name](spark, d).collect()} for d in (SMALL, OTHER))
    assert one and set(one) == set(two)
    return [(one[k], two[k]) for k in one]


def test_separability_gap_follows_the_rows(spark):
    assert sum(x.gap != y.gap for x, y in both(spark, "separability_gap", "dim", "variant", "measure")) == 14


def test_verdicts_are_those_of_the_measured_scenarios(spark):
    long = experiment.table_results(spark, SMALL).toPandas()
    v = {(r.variant, r.measure, r.scenario): r.value for r in long.itertuples()}
    rows = catalog.queries()["detection_flags"](spark, SMALL).collect()
    assert len(rows) == len(v) == 2 * 4 * 7
    for r in rows:
        a, b, c, d = (v[r.variant, r.measure, s] for s in "abcd")
        assert r.correct == {"a": a < b, "b": a < b, "c": c < min(b, d), "d": d > max(a, c)}[r.scenario]
    counts = {r.measure: r.n_correct for r in catalog.queries()["detection_counts"](spark, SMALL).collect()}
    assert counts == {m: sum(r.correct for r in rows if r.measure == m) for m in counts} and len(counts) == 7


def test_cost_model_counts_the_pairs_of_the_table(spark):
    for x, y in both(spark, "cost_model", "dim", "measure"):
        assert x.flops == y.flops and x.n_pairs < y.n_pairs and x.total == x.flops * x.n_pairs


def test_time_multiple_is_that_of_the_fastest_hour(spark):
    assert any(x.multiple != y.multiple for x, y in both(spark, "time_multiple", "dim", "scenario", "measure"))
    # one event has no pace, nor have events that fall together
    rows = spark.createDataFrame([("u", "2024-01-01 03:00:00"), ("u", "2024-01-02 04:00:00"), ("u", "2024-01-02 04:00:00"), ("u", "2024-01-01 05:00:00"), ("u", "2024-01-03 05:00:00")], "event_type string, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    got = {r.measure: r.multiple for r in experiment.multiples(experiment.event_paces(rows)).collect()}
    assert got == {"03": None, "04": None, "05": 1.0}


def test_pair_grid_measures_the_clusters_of_lineitem(spark):
    one = experiment.run_pair_grid(spark, (2, 4), reps=1, sf_dir=SMALL).toPandas()
    assert len(one) == 2 * 4 * 7 and (one["micros"] > 0).all() and (one["multiple"] >= 1).all()
    want = experiment.table_results(spark, SMALL).filter("variant = 'narrow'").toPandas()
    both_ = one[one["dim"] == 2].merge(want, on=["scenario", "measure"])
    assert len(both_) == 28 and np.allclose(both_["value_x"], both_["value_y"], rtol=1e-8)
    pair = experiment.table_pairs(spark, SMALL, 4)["c"][1]
    assert pair[1].shape == (4,) and pair[2].shape == (4, 4) and pair[2][0, 1] == pytest.approx(pair[2][1, 0])
