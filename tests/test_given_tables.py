"""Queries that once made up their data: what they return depends on the rows of a given table."""

from datetime import datetime, timedelta

import pytest

import __spark_entry__ as contract
from subwin.plans import rules

START = datetime(2024, 1, 1)


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Two series of one event an hour for thirty days, and 1,000 orders."""
    found = tmp_path_factory.mktemp("given")
    rows = [(i, START + timedelta(minutes=30 * i + 1), i % 7, "ab"[i % 2], float(i % 100), '{"k": 1}') for i in range(1440)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.parquet(f"{found}/events.parquet")
    spark.range(1000).selectExpr("id AS o_orderkey").coalesce(1).write.parquet(f"{found}/orders.parquet")
    return str(found)


def _rows(spark, folder, name):
    found = contract.queries()[name](spark, folder)
    assert found.inputFiles()
    return found.collect()


def test_result_cache(spark, folder):
    assert [tuple(r) for r in _rows(spark, folder, "baseline_result_cache")] == [(1, 2, 3 * 21 * 2, 99.0)]


def test_bounds(spark, folder):
    found = {(r["query"], r["series"], r["k"]): r for r in _rows(spark, folder, "bound_kll")}
    assert len(found) == 5 * 2 * 2 and found["full", "a", 20]["n_low"] == 720
    middle = found["middle", "b", 50]
    assert (middle["n_low"], middle["n_high"], middle["suffix"], middle["ranged"]) == (432, 216, 0.05, 0.09)


def test_registry(spark, folder):
    assert {(r["family"], r["samples"]) for r in _rows(spark, folder, "cache_registry")} == {("univ", 96), ("kll", 480), ("sample", 240)}


def test_ring(spark, folder):
    assert [tuple(r) for r in _rows(spark, folder, "cache_ring")] == [(1000, True, True)]


def test_sync(spark, folder):
    assert {tuple(r) for r in _rows(spark, folder, "cache_sync")} == {("ev_type", "sample", 240), ("ev_type", "univ", 96)}


def test_prices(spark, folder):
    found = {r["what"]: r["dollars"] for r in _rows(spark, folder, "cost_prices")}
    assert found == {"rescan_a_day": 0.002074, "rescan_a_month": 0.062208, "once_a_month": 0.0, "flat_ingestion": 5e-05}


def test_samples_scanned(spark, folder):
    assert {tuple(r) for r in _rows(spark, folder, "cost_samples_scanned")} == {("a", 3600, 720), ("b", 3600, 720)}


def test_coverage(spark, folder):
    found = _rows(spark, folder, "coverage_report")
    assert len(found) == len(rules.coverage()) and {r["samples"] for r in found} == {480}


def test_routes(spark, folder):
    found = {r["rule"]: (r["source"], r["samples"]) for r in _rows(spark, folder, "route_rules")}
    assert len(found) == 7 and found["distinct_short"] == ("cache", 48) and found["q90_long"] == ("exact", 480)


def test_eval_points(spark, folder):
    found = _rows(spark, folder, "rule_eval_points")
    assert len(found) == 7 * 21 and {r["samples"] for r in found if r["rule"] == "entropy"} == {96}


def test_other_label(spark, folder):
    """A label that the series lack is empty: it differs from any value, and equals none but the empty one."""
    assert len(_rows(spark, folder, "rule_other_label")) == 21 * 2
    assert rules._rule('max_over_time(ev_type{host="click"}[5d])')(spark, folder).isEmpty()
    assert rules._rule('max_over_time(ev_type{host=""}[5d])')(spark, folder).count() == 21 * 2
