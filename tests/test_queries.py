import pytest

from langspan import catalog
from tests.oracle import same


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_equals_sql(spark, sf, name):
    same(spark, sf, catalog.QUERIES[name], catalog.ORACLES[name])


def test_flagship_has_rows(spark, sf):
    rows = catalog.flagship(spark, sf).collect()
    assert rows and all(r["correct"] <= r["n"] for r in rows)
