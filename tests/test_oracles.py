"""Every query of the library with SQL gives what DuckDB gives."""

import pytest
from checks import same

from selsketch.registry import ORACLE, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query(spark, small, name):
    same(spark, small, QUERIES[name], ORACLE[name])
