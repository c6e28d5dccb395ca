"""Queries of worked examples read a given table."""

import pytest
from conftest import SF
from test_entry import canon, con  # noqa: F401

import __spark_entry__ as entry

NAMES = ["boundary_empty", "boundary_ties", "encode_example", "privacy_ratio", "space_table", "theory_covariance"]


@pytest.mark.parametrize("name", NAMES)
def test_a_given_table_is_read_and_sql_agrees(spark, con, name):  # noqa: F811
    df = entry.queries()[name](spark, SF)
    assert df.inputFiles() and df.count() > 0
    assert canon(df.toPandas()) == canon(con.execute(entry.oracle_sql()[name]).df())
