"""Every registered query of the library against its SQL, and those without SQL for rows."""

import pytest

from tests.conftest import FULL, check_query
from tilestar import registry

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, duck, name):
    check_query(spark, duck, QUERIES, ORACLES, name)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_gives_rows(spark, name):
    assert QUERIES[name](spark, FULL).count() > 0
