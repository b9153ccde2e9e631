from __future__ import annotations

import pytest
from conftest import SF, same_rows

from pathalgebra.llm import queries

QUERIES, ORACLE = queries.queries(), queries.oracle_sql()


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query(spark, duck, name):
    same_rows(QUERIES[name](spark, SF), duck, ORACLE[name])


