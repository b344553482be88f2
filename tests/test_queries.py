"""Every core query against its SQL on the smallest tables."""

import pytest

import __spark_entry__ as entry
from stratamatch import workloads

from .oracle import assert_same

workloads.load()


@pytest.mark.parametrize("name", sorted(workloads.SQL))
def test_query_equals_sql(spark, small, name):
    folder = small
    if name == "treatment_partition":  # the stated partition is that of the larger tables
        folder = "/root/testdata/sf0.01"
    assert_same(workloads.QUERIES[name](spark, folder), workloads.SQL[name], folder)


def test_entry_has_one_row(spark):
    row = entry.entry(spark).first()
    assert row["n"] == row["n1"] + row["n0"] > 0


def test_columns_of_queries_and_sql_are_registered():
    assert set(workloads.SQL) <= set(workloads.QUERIES)
