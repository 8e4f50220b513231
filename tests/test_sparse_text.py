import hashlib
from collections import Counter, defaultdict

from foldstar.plans import around as A


def test_words_are_in_the_gram(spark, tmp_path):
    SF = str(tmp_path)
    rows = [(1, "de", "src3", "One two two\nthree"), (2, "en", "src3", "two four one"), (3, "fr", "src19", None), (4, "es", "src0", "unlabelled")]
    spark.createDataFrame(rows, "doc_id long, lang string, source string, text string").coalesce(1).write.parquet(f"{SF}/documents.parquet")
    spark.createDataFrame([(1, 1, 0), (1, 1, 1), (2, 0, 1), (3, 1, 1), (9, 1, 1)], "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{SF}/labels.parquet")
    docs = {r["doc_id"]: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    want = defaultdict(float)
    for r in spark.read.parquet(f"{SF}/labels.parquet").collect():
        if r["doc_id"] not in docs:
            continue
        d = docs[r["doc_id"]]
        x = Counter(26 + int(hashlib.md5(w.encode()).hexdigest()[:8], 16) % 4096 for w in (d["text"] or "").lower().split())
        x |= {c: v for c, v in ((0, float(r["quality"])), (1, float(r["toxic"]))) if v}
        x |= {2 + i: 1 for i, v in enumerate(["de", "en", "es", "fr"]) if d["lang"] == v} | {6 + i: 1 for i in range(20) if d["source"] == f"src{i}"}
        cells = sorted(x.items())
        for k, (i, u) in enumerate(cells):
            for j, v in cells[k:]:
                want[i, j] += u * v
    got = {(r["i"], r["j"]): r["value"] for r in A.LONG["gram_sparse_text_documents"](spark, SF).collect()}
    assert got == dict(want) and max(j for _, j in got) > 26


def test_gram_of_cells_in_arrays(spark, monkeypatch):
    from foldstar import normalized

    cells = spark.createDataFrame([(1, 0, 2.0), (1, 3, -1.0), (1, 3, 4.0), (2, 3, 5.0), (2, 1, 1.0), (3, 2, 7.0)], "k long, col int, val double")
    coo = normalized.Coo(cells, "k", list("abcd"), cells.select("k").distinct())
    hits = spark.createDataFrame([(1, 2), (2, 3)], "k long, _hits long").withColumnRenamed("k", "f")
    read = lambda: sorted(tuple(r) for r in coo.gram_long(hits, "f").select("i", "j", "value").collect())
    got, plan = read(), coo.gram_long(hits, "f")._jdf.queryExecution().optimizedPlan().toString()
    monkeypatch.setattr(normalized, "DENSE_WIDTH", 0)
    assert got == read() and plan.count("Join") == 1
