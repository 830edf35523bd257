"""Every query of the classifier methods against its SQL twin on the smallest tables."""

import math

import pytest

from dp_margin.queries import ORACLES, QUERIES, flagship

#: Their SQL or thresholds speak about larger tables than the smallest ones.
SLOW = {"ml_crosscheck", "map_poly2"}


def rows(frame):
    """Column names, and rows in an order that the last digits of numbers don't change."""
    cols = sorted(frame.columns)

    def plain(x):
        if isinstance(x, float) and not math.isnan(x):
            return float(f"{x + 0.0:.6g}")
        return "null" if x is None or x != x else float(x) if isinstance(x, int) and not isinstance(x, bool) else str(x)

    return cols, sorted((tuple(plain(v) for v in r) for r in frame[cols].itertuples(index=False, name=None)), key=repr)


def same(a, b):
    return a == b or (isinstance(a, float) and isinstance(b, float) and math.isclose(a, b, rel_tol=2e-5, abs_tol=2e-6))


@pytest.mark.parametrize("name", sorted(set(ORACLES) - SLOW))
def test_query_equals_sql(spark, sf, duck, name):
    import pandas as pd

    got = QUERIES[name](spark, sf).toPandas()
    want = duck.execute(ORACLES[name]).df()
    for d in (got, want):
        for c in d.columns:
            if pd.api.types.is_bool_dtype(d[c].dtype) or d[c].dtype == object:
                continue
            if pd.api.types.is_numeric_dtype(d[c].dtype):
                d[c] = d[c].astype("float64")
            elif pd.api.types.is_datetime64_any_dtype(d[c].dtype):
                d[c] = d[c].dt.strftime("%Y-%m-%d")
    (gc, gr), (wc, wr) = rows(got), rows(want)
    assert gc == wc
    assert len(gr) == len(wr)
    assert all(same(a, b) for x, y in zip(gr, wr, strict=True) for a, b in zip(x, y, strict=True))


def test_flagship(spark, sf):
    out = flagship(spark, sf)
    assert out.columns == ["pos", "w"] and out.count() == 4
