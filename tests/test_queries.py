"""Every registered query of the engine against its SQL at the smallest scale, and the registry's shape."""

import pytest

from skewtile import relational, workloads
from tests.conftest import SMALL
from tests.oracle import connect, same

QUERIES = {**workloads.QUERIES, **relational.QUERIES}
SQL = {**workloads.SQL, **relational.SQL}


@pytest.fixture(scope="module")
def con():
    return connect(SMALL)


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_as_sql(spark, con, name):
    same(QUERIES[name](spark, SMALL), con, SQL[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(SQL) - {"filter_adaptive_round2", "filter_adaptive_knn", "planner_cost_before_after", "planner_cost_sampled"}))
def test_runs(spark, name):
    assert QUERIES[name](spark, SMALL).count() >= 0


def test_entry(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() == 39


@pytest.mark.parametrize("name", ["udf_area_label", "udf_haversine", "haversine", "wkb_points"])
def test_all_events_are_computed(spark, name):
    assert QUERIES[name](spark, SMALL).count() == spark.read.parquet(f"{SMALL}/events.parquet").count()


def test_shapes_meet_all_rows(spark):
    """The searched side is whole: paths of all users."""
    assert any(r[0] % 20 for r in QUERIES["shape_join_paths_boxes"](spark, SMALL).collect())


@pytest.mark.parametrize("name", ["generated_queries", "planner_running_example"])
def test_worked_queries_read_events(spark, name, monkeypatch):
    """Nothing is made up: the rows come from the events."""
    from skewtile.sources import planes

    read, whole = [], planes.events
    monkeypatch.setattr(planes, "events", lambda *a: read.append(1) or whole(*a))
    assert QUERIES[name](spark, SMALL).count() == (1000 if name == "generated_queries" else 3) and read
