"""Every query with a DuckDB twin gives the twin's rows; the others give rows."""

import pytest

from avcurate.queries import ORACLES, QUERIES
from compare import SMALL, same


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_twin(spark, duck, name):
    same(spark, duck, QUERIES[name], ORACLES[name], SMALL)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - {"w7_compare"}))
def test_rows(spark, name):
    assert QUERIES[name](spark, SMALL).count() > 0


def test_entry():
    import __spark_entry__ as e

    assert set(ORACLES) <= set(e.oracle_sql()) and set(QUERIES) <= set(e.queries())
    assert set(e.oracle_sql()) <= set(e.queries())
