"""Scores over a join index: before the last join only its sides are on disk."""

import os
import time

import numpy as np
import pytest

from foldstar import pairs
from foldstar.workloads import FIXTURES

SF = "/root/testdata/sf0.001"


def shuffle_files(spark):
    found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {found.apply(i).getName() for i in range(found.size()) if found.apply(i).getName().startswith("shuffle")}


@pytest.mark.parametrize("call", ["lmm", "row_sums"])
def test_only_the_sides_of_the_last_join_stay(spark, monkeypatch, call):
    t = FIXTURES["ch"].build(spark, SF)
    had = shuffle_files(spark)
    made, cut = [], pairs.cut
    monkeypatch.setattr(pairs, "cut", lambda *a: made.append(cut(*a)) or made[-1])
    got = t.row_sums() if call == "row_sums" else t @ np.ones(t.d)
    for _ in range(100):
        if not (left := shuffle_files(spark) - had):
            break
        time.sleep(0.1)
    assert not left
    there = [f._cut_at for f in made if os.path.exists(f._cut_at.removeprefix("file:"))]
    assert len(made) > 2 and len(there) == 2 and all("pair-side" in x for x in there)
    ids = list(FIXTURES["ch"].ids.values())
    sort = lambda r: sorted(tuple(v) for v in r.frame.select(*ids, *r.cols).collect())
    assert sort(got) == sort(t.explicit() @ np.ones(t.d))
