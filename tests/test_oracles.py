"""Queries against DuckDB on the smallest tables; SQL is written apart from the Spark code."""

import pandas as pd
import pytest

from fieldmr import catalog

SF = "/root/testdata/sf0.001"
WITH_SQL = sorted(catalog.oracle_sql())


def rows(df):
    def plain(v):
        if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and v != v):
            return None
        return v.item() if hasattr(v, "item") else v

    df = df[sorted(df.columns)]
    return sorted((tuple(map(plain, r)) for r in df.itertuples(index=False)), key=repr)


@pytest.mark.parametrize("name", WITH_SQL)
def test_query_matches_sql(spark, duck, name):
    got, want = catalog.queries()[name](spark, SF).toPandas(), duck.sql(catalog.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_flagship_keeps_bounds(spark):
    points = catalog.flagship(spark, SF).toPandas()
    assert len(points) == 10
    assert (points.max_err <= points.eb).all()
    assert (points.cr > 1).all()
