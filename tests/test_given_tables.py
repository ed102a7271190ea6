"""Queries that once made their data up read given tables."""

import pytest

import __spark_entry__ as entry

NAMES = [
    "map_signs",
    "metapath_len",
    "metric_direction",
    "relative_gain",
    "worked_example",
]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_given_table(spark, tiny, name):
    assert any(f.endswith(".parquet") and "sf0.001" in f for f in entry.queries()[name](spark, tiny).inputFiles())
