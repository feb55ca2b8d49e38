"""Queries that once made their data up read a table: their plans scan it and results follow it."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from conftest import DATA
from heavyhitters.functions import cost


@pytest.mark.parametrize("name, file", [*((f"cost_{c}", "lineitem") for c in ("comm", "depth", "isoefficiency", "scalability", "time_model")), ("gen_range_join", "events"), ("op_scan_range", "events")])
def test_the_plan_scans_a_table(spark, name, file):
    assert f"{file}.parquet" in entry.queries()[name](spark, DATA)._jdf.queryExecution().executedPlan().toString()


def test_rate_numbers_are_events(spark):
    types = {r[0] for r in spark.read.parquet(f"{DATA}/events.parquet").select("event_type").distinct().collect()}
    assert {(r.item, r.whole, r.some) for r in entry.queries()["src_rate"](spark, DATA).collect()} == {(t, True, True) for t in types}


def test_workers_by_day(spark):
    rows = spark.createDataFrame([("2024-01-02 10:00:00",), ("2024-01-01 09:00:00",), ("2024-01-02 23:00:00",), (None,)], "at string").select(F.col("at").cast("timestamp").alias("at"))
    assert sorted(map(tuple, cost.daily(rows, "at").collect())) == [(1, 3), (2, 3)]
