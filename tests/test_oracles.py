"""Every query that has SQL gives the same rows as DuckDB on the smallest tables."""

import pytest

from tests.conftest import same_rows
from wordset import queries, queries_experiments, queries_relational  # noqa: F401


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, duck, sf, name):
    same_rows(queries.QUERIES[name](spark, sf), duck, queries.ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - set(queries.ORACLES)))
def test_query_without_sql_runs(spark, sf, name):
    assert queries.QUERIES[name](spark, sf).count() > 0
