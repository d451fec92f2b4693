"""What is registered reads a given table."""

from dyntri import queries
from dyntri.plans import methods


def test_fixed_statements_are_no_query(spark):
    assert "capabilities" not in queries.queries() and "capabilities" not in queries.oracle_sql()
    assert methods.capabilities(spark).count() == 48
