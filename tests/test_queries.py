"""Every registered query against its SQL on the smallest tables."""

from __future__ import annotations

import pytest
from conftest import SF, same_rows

from pathalgebra import workloads

QUERIES, ORACLE = workloads.queries(), workloads.oracle_sql()


def test_every_oracle_has_a_query():
    assert set(ORACLE) <= set(QUERIES)


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query(spark, duck, name):
    same_rows(QUERIES[name](spark, SF), duck, ORACLE[name])


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 10
