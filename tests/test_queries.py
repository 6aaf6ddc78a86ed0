import pytest

import __spark_entry__ as entry
from sketchlearn.plans import oracles, relational, relational_oracles, variances, workloads

from .oracle import compare

QUERIES = workloads.QUERIES | relational.QUERIES | variances.QUERIES
SQL = oracles.ORACLES | relational_oracles.ORACLES | variances.ORACLES


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, name):
    compare(spark, QUERIES[name], SQL[name])


def test_entry(spark):
    assert entry.entry(spark).columns == ["id", "j", "z"]


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
