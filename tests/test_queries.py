"""Every registered query of the engine against SQL that joins first, at the smallest scale."""

import pytest

from foldstar.plans import around
from foldstar.plans import queries as algebra
from tests.compare import assert_same

SF = "/root/testdata/sf0.001"
ALL = algebra.QUERIES | around.QUERIES
SQL = algebra.ORACLES | around.ORACLES


@pytest.mark.parametrize("name", sorted(ALL))
def test_query(spark, name):
    assert name in SQL
    assert_same(ALL[name](spark, SF), SQL[name], SF)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_factored_plan_moves_scores_not_features(spark):
    from foldstar.workloads import FIXTURES

    t = FIXTURES["k1"].build(spark, SF)
    scores = t.links[0].block.scores(__import__("numpy").ones((33, 1)), "_s0_")
    assert scores.columns == ["_key", "_s0_0"]
    r = t.scored(__import__("numpy").ones((t.d, 1)))
    assert not set(t.links[0].block.names) & set(r.frame.columns)
    above = r.frame._jdf.queryExecution().optimizedPlan().toString().split("Join Inner")[0]
    assert "p_br" not in above and "_s0_0" in above
    assert t.explain().startswith("star")
