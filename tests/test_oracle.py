"""Every query of the catalogue against its SQL on the smallest tables; those without SQL must run."""

import pytest
from oracle import SF, compare

from writelite import catalog

QUERIES, SQL = catalog.queries(), catalog.oracle_sql()


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, name):
    if name in SQL:
        compare(spark, QUERIES[name], SQL[name])
    else:
        assert QUERIES[name](spark, SF).count() > 0


def test_entry_points(spark):
    import __spark_entry__

    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert "pos" in __spark_entry__.entry(spark).columns
