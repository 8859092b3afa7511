"""Every query with SQL gives the rows of its SQL, at the smallest scale."""

import pytest
from helpers import rows

from fieldseg.plans import oracles, queries

SQL = oracles.build()
QUERIES = queries.build()


def test_all_sql_has_a_query():
    assert set(SQL) <= set(QUERIES)


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, duck, sf, name):
    got = QUERIES[name](spark, sf)
    if name in SQL:
        assert rows(got) == rows(duck.sql(SQL[name]).df())
    else:
        assert got.count() > 0
