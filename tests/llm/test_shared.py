import pytest
from pyspark.sql import functions as F

from foldstar.llm import quality, shared


def test_filter_keeps_every_column(spark):
    df = spark.createDataFrame([(1, "x", 5), (2, "y", 6)], "a long, _at string, _at_ int")
    got = shared.filtered(df, F.col("a") > 1)
    assert got.columns == df.columns and [tuple(r) for r in got.collect()] == [(2, "y", 6)]


def test_quality_stage_with_clashing_column(spark):
    df = spark.createDataFrame([(1, None, "kept"), (2, "a b", "kept")], "doc_id long, text string, _at string")
    assert quality.keep_good(df).columns == df.columns and quality.keep_good(df).count() == 0


def test_cluster_needs_a_shared_folder():
    class Conf:
        def get(self, *_):
            return None

    class Context:
        master = "spark://somewhere:7077"

        def getConf(self):  # noqa: N802
            return Conf()

    class Session:
        conf, sparkContext = Conf(), Context()  # noqa: N815

    with pytest.raises(RuntimeError):
        shared.shared_dir(Session())


def test_stages_leave_one_table_each(spark, tmp_path, monkeypatch):
    import corpus_pipeline as C

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").limit(60)
    for stage, left in ((C.line_stage, "deleted-lines"), (C.near_duplicate_stage, "kept-keys"), (C.substring_stage, "ranges")):
        monkeypatch.setattr(shared, "shared_dir", lambda _, at=str(tmp_path / left): at)
        assert stage(spark, docs, None).count() > 0
        assert [p.name.rsplit("-", 1)[0] for p in (tmp_path / left / "foldstar").iterdir()] == [left]


def test_settled_keeps_what_an_outer_step_made(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(shared, "shared_dir", lambda _: str(tmp_path))

    def outer():
        a = shared.stored(spark.range(5), "a")
        b = shared.settled(lambda: shared.stored(a.where("id > 1"), "inner"), "b")
        assert a.count() == 5 and b.count() == 3
        return a.join(b, "id")

    assert shared.settled(outer, "c").count() == 3
    assert [p.name[0] for p in (tmp_path / "foldstar").iterdir()] == ["c"]
