"""Every registered query with SQL, against DuckDB on the smallest tables."""

import math

import pytest

import __spark_entry__ as entry
from conftest import DATA
from heavyhitters import registry, registry_more  # noqa: F401

SQL = registry.SQL


def plain(value):
    if isinstance(value, float):
        return "nan" if math.isnan(value) else float(f"{value:.9g}")
    return tuple(map(plain, value)) if isinstance(value, (list, tuple)) else value


def table(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(columns), sorted((tuple(plain(r[i]) for i in order) for r in rows), key=repr)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query(spark, duck, name):
    got = entry.queries()[name](spark, DATA)
    result = duck.sql(SQL[name])
    assert table(got.columns, [tuple(r) for r in got.collect()]) == table(result.columns, result.fetchall())
    spark.catalog.clearCache()


def test_entry(spark):
    assert entry.entry(spark).columns == ["item", "est", "err", "lower", "status"]


def test_names_agree():
    assert set(entry.oracle_sql()) <= set(entry.queries())
