from foldstar.llm import quality as Q
from tests.compare import assert_same

SF = "/root/testdata/sf0.001"


def test_query_matches_sql(spark):
    assert_same(Q.op5_quality_rules(spark, SF), Q.OP5_SQL, SF)


def _repeat(words):
    wins = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    hit = {i + k for i, x in enumerate(wins) if wins.count(x) > 1 for k in range(3)}
    return len(hit)


def test_defined_cases(spark):
    texts = [None, "", "a", "a b c a b c", "a b c b a b c d", "x\ty\x0bz x y z", "same line\nsame line\n\n \nother", "w " * 3000, "no break"]
    df = spark.createDataFrame([(i, t, "k") for i, t in enumerate(texts)], "doc_id long, text string, _m string")
    got = {r["doc_id"]: r["m2"] for r in Q.judge(df, into="m2").collect()}
    for i, t in enumerate(texts):
        w = (t or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ")
        w = [x for x in w if x]
        assert got[i]["n_words"] == len(w)
        assert got[i]["word_chars"] == sum(map(len, w))
        assert got[i]["n_repeat_words"] == (_repeat(w) if len(w) < 100 else len(w))
        assert got[i]["base_failed"] == (len(w) < 50 or 100 * got[i]["n_repeat_words"] > 50 * len(w))
    assert got[6]["n_dup_lines"] == 1
    assert Q.keep_good(df.limit(0)).count() == 0
    assert Q.keep_good(df).columns == df.columns


def test_slow_way_equals_quick_way(spark, monkeypatch):
    rows = [(i, " ".join("abcde"[(i * 7 + j * j) % 5] for j in range(3 + i))) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    quick = {r[0]: r[1] for r in Q.judge(df).select("doc_id", "_m.n_repeat_words").collect()}
    monkeypatch.setattr(Q, "_PLACE", 1)
    slow = {r[0]: r[1] for r in Q.judge(df).select("doc_id", "_m.n_repeat_words").collect()}
    assert quick == slow == {i: _repeat(t.split()) for i, t in rows}
