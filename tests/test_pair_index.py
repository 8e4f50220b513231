import numpy as np
import pytest
from pyspark.sql import functions as F

from foldstar import algos, pairs
from foldstar.plans import queries as Q
from foldstar.workloads import FIXTURES
from tests.compare import assert_same

SF = "/root/testdata/sf0.001"


def unmade(spark, name):
    """The fixture over rows that fail when they are read: only its tables are left."""
    t = FIXTURES[name].build(spark, SF)
    t.rows = t.rows.withColumn("_p0", F.raise_error(F.lit("the pairs were made")).cast("long"))
    return t


@pytest.mark.parametrize("name", ["mn", "ch"])
def test_col_sums_make_no_pairs(spark, name):
    t = FIXTURES[name].build(spark, SF)
    assert (unmade(spark, name).col_sums() == t.explicit().col_sums()).all()


@pytest.mark.parametrize("name", ["mn", "ch"])
def test_gram_makes_no_pairs(spark, name):
    t = FIXTURES[name].build(spark, SF)
    assert (unmade(spark, name).gram() == t.explicit().gram()).all()


def test_naive_gram_makes_no_pairs(spark):
    t = FIXTURES["mn"].build(spark, SF)
    assert (unmade(spark, "mn").gram(method="naive") == t.explicit().gram(method="naive")).all()


@pytest.mark.parametrize("name", ["mn", "ch"])
def test_scores_cross_no_shuffle_as_pairs(spark, name):
    ids = list(FIXTURES[name].ids.values())
    t, x = FIXTURES[name].build(spark, SF), np.arange(len(FIXTURES[name].features), dtype=float)
    sort = lambda r: sorted(tuple(v) for v in r.frame.select(*ids, *r.cols).collect())
    got = unmade(spark, name) @ x
    assert sort(got) == sort(t.explicit() @ x)
    few = t[["c_bal"]]
    assert sort(few @ [2.0]) == sort(few.explicit() @ [2.0])
    top = got.frame._jdf.queryExecution().executedPlan().toString().split("Join", 1)[0]
    assert "Exchange hash" not in top


@pytest.mark.parametrize("block", [1000, 7])
def test_gradient_makes_no_pairs(spark, block, monkeypatch):
    monkeypatch.setattr(pairs, "BLOCK", block)
    label = lambda a, b: 1.0 - 2.0 * ((a + b) % 2) * ((a + b) % 2)
    t = FIXTURES["mn"].build(spark, SF).labelled("y", label)
    want = algos.logistic_gd(t.explicit(), "y", alpha=1e-9, iters=2)
    t.rows = t.rows.withColumn("_p0", F.raise_error(F.lit("the pairs were made")).cast("long"))
    assert np.allclose(algos.logistic_gd(t, "y", alpha=1e-9, iters=2), want, rtol=1e-9, atol=0)


@pytest.mark.parametrize("name", ["col_sums_ch", "gram_ch", "lmm_ch", "row_sums_ch", "gram_mn_naive", "logistic_gd_mn"])
def test_queries_on_pairs(spark, name):
    assert_same(Q.QUERIES[name](spark, SF), Q.ORACLES[name], SF)
