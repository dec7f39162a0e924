"""Every registered query of the engine against its SQL on the smallest tables."""

import numbers

import pandas as pd
import pytest
from conftest import SMALL

from clusterfuse.plans import catalog


def rows_of(df):
    """Rows as (what is no number, numbers), in one order. Whole numbers come as floats where a column has nulls, so all are floats here."""
    cols = sorted(df.columns)
    out = []
    for row in df[cols].itertuples(index=False):
        plain, floats = [], []
        for v in row:
            if isinstance(v, numbers.Real) and not isinstance(v, bool) and not pd.isna(v):
                floats.append(float(v))
                plain.append("number")
            else:
                plain.append("null" if pd.api.types.is_scalar(v) and pd.isna(v) else str(v))
        out.append((plain, floats))
    return cols, sorted(out, key=lambda x: (x[0], [round(v, 3) for v in x[1]]))


@pytest.mark.parametrize("name", sorted(catalog.queries()))
def test_query(spark, duck, name):
    got = catalog.queries()[name](spark, SMALL).toPandas()
    sql = catalog.oracle_sql().get(name)
    if sql is None:
        assert len(got) > 0
        return
    (cols, a), (wanted, b) = rows_of(got), rows_of(duck.sql(sql).df())
    assert cols == wanted and len(a) == len(b)
    for (plain, floats), (plain_, floats_) in zip(a, b):
        assert plain == plain_
        for x, y in zip(floats, floats_, strict=True):
            # only a rounded fraction may lie on the other side of a tie
            assert x == y or not (x.is_integer() and y.is_integer()) and x == pytest.approx(y, rel=1e-6, abs=1.1e-4)
