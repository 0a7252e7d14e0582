"""Queries on tables with larger values, and on plans that have to hold as the tables grow."""

import duckdb
import pytest
from test_oracles import rows

from fieldmr import catalog

SF = "/root/testdata/sf0.001"


def same_as_sql(spark, folder, name):
    c = duckdb.connect()
    for p in folder.glob("*.parquet"):
        c.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    got, want = catalog.queries()[name](spark, str(folder)).toPandas(), c.sql(catalog.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert len(got) and rows(got) == rows(want)


@pytest.fixture(scope="module")
def rich(tmp_path_factory):
    """Events of ten thousand times the value: fifty times the bound of the density passes 2^31, four times the bound does not."""
    folder = tmp_path_factory.mktemp("rich")
    duckdb.sql(f"COPY (SELECT * REPLACE (value * 10000 AS value) FROM '{SF}/events.parquet') TO '{folder}/events.parquet'")
    return folder


def test_fit_grid_with_large_values(spark, rich):
    same_as_sql(spark, rich, "repair_fit_grid")


def test_range_join_broadcasts_nothing(spark):
    plan = catalog.queries()["op_join_range"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


@pytest.fixture(scope="module")
def short(tmp_path_factory):
    """Users of 1 to 35 events, values that are null or all alike, and events of no user."""
    folder = tmp_path_factory.mktemp("short")
    events = """SELECT * REPLACE (CASE WHEN u = 0 THEN NULL ELSE u END AS user_id, CASE WHEN u = 7 OR i = 3 THEN NULL WHEN u = 9 THEN 5.0 ELSE value END AS value), FROM
(SELECT e.*, u, i FROM range(36) AS a(u), range(36) AS b(i), (SELECT * FROM '{0}/events.parquet') e WHERE i < greatest(u, 1) AND e.event_id = 36 * (u // 2) + i)"""
    duckdb.sql(f"COPY (SELECT * EXCLUDE (u, i) FROM ({events.format(SF)})) TO '{folder}/events.parquet'")
    return folder


def reads(spark, name, file):
    assert any(f.endswith(file) for f in catalog.queries()[name](spark, SF).inputFiles())


@pytest.mark.parametrize("name", ["interp_plan_n", "interp_extrapolated_count", "interp_schedule_paper", "interp_schedule_flat", "interp_schedule_coarse"])
def test_lines_come_from_events(spark, short, name):
    reads(spark, name, "events.parquet")
    same_as_sql(spark, short, name)


def test_size_plan_comes_from_lineitem(spark):
    reads(spark, "metric_size_plan", "lineitem.parquet")
