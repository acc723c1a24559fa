"""The driver's contract."""

import importlib


def test_queries_and_oracles():
    entry = importlib.import_module("__spark_entry__")
    names = set(entry.queries())
    assert len(names) > 180 and set(entry.oracle_sql()) <= names


def test_entry(spark):
    entry = importlib.import_module("__spark_entry__")
    rows = entry.entry(spark).collect()
    assert len(rows) == 1 and rows[0]["apart"] == 0
