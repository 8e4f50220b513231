import pytest

from foldstar.llm import registry
from tests.compare import assert_same


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_query_matches_sql(spark, name):
    assert_same(registry.QUERIES[name](spark, "/root/testdata/sf0.01"), registry.ORACLES[name], "/root/testdata/sf0.01")
